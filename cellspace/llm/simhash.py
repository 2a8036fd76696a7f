"""Near duplicates by SimHash, found with pigeonhole blocks.

``SEEDS`` fingerprints of 64 bits are made of damped word counts (1 + ln n) of the folded text, and a check
fingerprint of 128 bits of the word triples. A fingerprint is cut into ``blocks`` pieces; two that differ in at most
``distance`` bits agree in ``blocks - distance`` pieces at least, so each choice of that many pieces is a key and
close pairs share one. Pairs that share a key are verified: at most ``distance`` bits of that fingerprint and at most
``check_distance`` of the check differ. Groups are the connected parts of these pairs, by spreading the least id. The pairs
themselves, as the square of a large group, are never written: the task of a key joins what is close, skips pairs of
rows that are joined already and gives a link from the least id to each other row of a part.

Equal fingerprints are one node, so copies by the thousand cost nothing. Pieces are chosen twice: a node is shuffled
under few short keys (one piece of eight for each fingerprint up to 2^28 nodes), and the task of a key cuts the other
bits into pieces again, in memory, as many as its rows need. Both change the cost only, never the pairs. What is shuffled
is fingerprints, not texts; a key carries its fingerprint and the check, so that only pairs that pass both leave the task
that finds them.

Rows are told apart by a number of their own, so ids may be of any type, null or repeated.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellspace.llm.common import WordIds, folded_words, map_batches, maybe_broadcast, mix, pieces, staged, word_hashes

SEEDS, CHECK_WORDS, BITS = 3, 2, 64
DISTANCE, CHECK_DISTANCE = 7, 40
#: Rows of a task that compares keys, and the least number of such tasks: with fewer, rows of one node share a block of
#: the shuffle and compress away, so that the bytes of a key would depend on the size of the input.
KEY_ROWS, KEY_TASKS = 400_000, 64
#: Rows that are compared together, the most rows of a key, and what a row costs to sort, in comparisons.
RUN_ROWS, CELL_ROWS, SORT_COST = 100_000, 1 << 20, 20
PRINT_COLS = [f"f{s}" for s in range(SEEDS)]
CHECK_COLS = [f"c{s}" for s in range(CHECK_WORDS)]


def _bits(hashes: np.ndarray, words: int, salt: int) -> np.ndarray:
    """Rows of ``64 * words`` bits (uint8) for 64-bit hashes."""
    cols = [mix(hashes + np.uint64((salt + k) * 0x9E3779B97F4A7C15 % 2**64)) for k in range(words)]
    return np.unpackbits(np.stack(cols, 1).view(np.uint8), axis=1)


def _packed(ones: np.ndarray) -> np.ndarray:
    return np.packbits(ones, axis=1).view(np.int64)


def _sums(values: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Sums of runs of rows, zero for empty runs."""
    out = np.zeros((len(lengths), values.shape[1]), np.int64)
    some = np.flatnonzero(lengths)
    if len(some):
        starts = np.concatenate([[0], np.cumsum(lengths)[:-1]])[some]
        out[some] = np.add.reduceat(values, starts, axis=0, dtype=np.int32)
    return out


def fingerprints(docs: list[list[bytes]], ids: WordIds, step: int = 100_000) -> np.ndarray:
    """[documents, SEEDS + CHECK_WORDS] of int64."""
    flat, lengths = ids(docs)
    signs, hashes = ids.rows
    width = int(flat.max()) + 1 if len(flat) else 1
    doc = np.repeat(np.arange(len(docs)), lengths)
    keys, n = np.unique(doc * width + flat, return_counts=True)
    who, weight = keys // width, np.rint(8 * (1 + np.log(n))).astype(np.int16)
    each = np.bincount(who, minlength=len(docs))
    total = np.zeros((len(docs), BITS * SEEDS), np.int64)
    check = np.zeros((len(docs), 64 * CHECK_WORDS), np.int64)
    h = hashes[flat]
    three = h + np.uint64(3) * np.roll(h, -1) + np.uint64(7) * np.roll(h, -2)
    left = np.cumsum(lengths)[doc] - np.arange(len(flat)) if len(flat) else np.zeros(0, np.int64)
    short = lengths[doc] < 3  # words of too short texts count alone
    use = (left >= 3) | short
    three, whose = np.where(short, h, three)[use], doc[use]
    triples = np.bincount(whose, minlength=len(docs))
    for lo, values, count, out in ((0, None, each, total), (0, None, triples, check)):
        ends = np.cumsum(count)
        at = 0
        while at < len(docs):
            base = ends[at - 1] if at else 0
            to = max(at + 1, int(np.searchsorted(ends, base + step, "right")))
            s = slice(base, ends[to - 1])
            if out is total:
                out[at:to] = _sums(signs[keys[s] % width].astype(np.int16) * weight[s, None], count[at:to])
            else:
                out[at:to] = 2 * _sums(_bits(three[s], CHECK_WORDS, 100), count[at:to]) - count[at:to, None]
            at = to
    return np.concatenate([_packed(total > 0), _packed(check > 0)], axis=1)


def word_rows(words: list[bytes]) -> list[np.ndarray]:
    h = word_hashes(words)
    return [(2 * _bits(h, SEEDS, 1).astype(np.int8) - 1).reshape(len(words), BITS * SEEDS), h]


def _kernel(carried: int):
    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids = WordIds(word_rows, 150_000)
        for part, texts in pieces(batches, carried, 1_500_000):
            words = [folded_words(t or "") for t in texts]
            prints = fingerprints(words, ids)
            n = pa.array([len(w) for w in words], pa.int64())
            names = [*part.schema.names[:carried], "words", *PRINT_COLS, *CHECK_COLS]
            yield pa.RecordBatch.from_arrays([*part.columns[:carried], n, *(pa.array(prints[:, k]) for k in range(SEEDS + CHECK_WORDS))], names=names)

    return kernel


def _printed(df: DataFrame) -> DataFrame:
    """The prints of each row; the last column of ``df`` is its text, the others stay."""
    carried = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema[:-1])
    cols = ", ".join(f"{c} long" for c in [*PRINT_COLS, *CHECK_COLS])
    return map_batches(df, _kernel(len(df.columns) - 1), f"{carried}, words long, {cols}")


def simhash_prints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, words, f0.., c0..) of each document with words; texts without any (null, empty, only signs) have none."""
    return _printed(docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))).where("words > 0")


def block_plan(nodes: int, distance: int = DISTANCE, width: int = BITS) -> list[tuple[tuple[int, int], ...]]:
    """Keys as lists of (first bit, bits): every choice of ``blocks - distance`` blocks."""
    return _choices(distance, 1 if nodes <= 1 << 28 else 2 if nodes <= 1 << 34 else 3, width)


def _choices(distance: int, take: int, width: int) -> list[tuple[tuple[int, int], ...]]:
    """Choices of ``take`` of ``distance + take`` blocks of ``width`` bits."""
    edges = np.linspace(0, width, distance + take + 1).round().astype(int)
    spans = [(int(a), int(b - a)) for a, b in zip(edges, edges[1:], strict=False)]
    return list(combinations(spans, take))


def _key(column: str, spans) -> F.Column:
    out = F.lit(0).cast("long")
    for first, bits in spans:
        out = F.shiftleft(out, bits).bitwiseOR(F.shiftrightunsigned(F.col(column), first).bitwiseAND(F.lit((1 << bits) - 1)))
    return out


def _bits_of(values: np.ndarray, spans) -> np.ndarray:
    """The bits of ``spans`` side by side; ``values`` are uint64."""
    out = np.zeros(len(values), np.uint64)
    for first, bits in spans:
        out = (out << np.uint64(bits)) | ((values >> np.uint64(first)) & np.uint64((1 << bits) - 1))
    return out


def _mask(spans) -> np.uint64:
    return np.uint64(sum(((1 << bits) - 1) << first for first, bits in spans))


def _others(spans) -> list[tuple[int, int]]:
    """The spans of a fingerprint between those of a key."""
    ends = [(0, 0), *spans, (BITS, 0)]
    return [(a + n, b - a - n) for (a, n), (b, _) in zip(ends, ends[1:], strict=False) if b > a + n]


def differing(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.bitwise_count((a ^ b).view(np.uint64))


def _run_ends(keys: np.ndarray, *more: np.ndarray) -> np.ndarray:
    """For each of sorted keys where its run of equal ones ends."""
    new = keys[1:] != keys[:-1]
    for x in more:
        new = new | (x[1:] != x[:-1])
    stops = np.append(np.flatnonzero(new) + 1, len(keys))
    return np.repeat(stops, np.diff(stops, prepend=0))


def _joined(part: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """``part`` (the least row of the part of each row) after rows ``i`` and ``j`` are joined."""
    part = part.copy()
    while len(i):
        a, b = part[i], part[j]
        apart = a != b
        i, j, a, b = i[apart], j[apart], a[apart], b[apart]
        np.minimum.at(part, np.maximum(a, b), np.minimum(a, b))
        while (part != (up := part[part])).any():
            part = up
    return part


def _verify(plan: list, distance: int, check_distance: int, memory: int = 500_000, links: bool = False):
    """Rows (key, cell, id, fingerprint, check) in order of key and cell: ids of all pairs that share both and are close
    in both prints. With ``links`` only as many as connect the same rows: the least id of each connected part of the rows
    that share both, with each other id of the part.

    Within a run of equal keys the other bits of the fingerprint are cut into blocks once more, so that only rows which
    agree in some choice of those too are compared. A pair is found by the first choice that it shares, of the keys and
    within a key. Whole runs are compared together, by offsets; only the last run of a batch is carried over.
    """
    masks = [_mask(spans) for spans in plan]

    def finer(run: np.ndarray, rest: np.ndarray, width: int, part: np.ndarray | None = None) -> list:
        """Choices of blocks of the ``width`` bits of ``rest``: more and longer ones the more pairs are left. Pairs within
        a ``part`` don't count."""
        best, least = [()], math.inf
        several = np.zeros(0, np.int64) if part is None else np.flatnonzero(np.bincount(part)[part] > 1)
        for take in range(5):
            choices = _choices(distance, take, width)
            own = (run << np.uint64(sum(n for _, n in choices[0]))) | _bits_of(rest, choices[0])
            left = 0
            if len(several):
                order = several[np.lexsort((part[several], own[several]))]
                left = -int((_run_ends(own[order], part[order]) - np.arange(1, len(order) + 1)).sum())
            own.sort()
            left += int((_run_ends(own) - np.arange(1, len(own) + 1)).sum())
            cost = len(choices) * (SORT_COST * len(own) + left)
            if cost >= least:
                break
            best, least = choices, cost
        return best

    def pairs(run: np.ndarray, rows: np.ndarray, at_plan: int) -> Iterator[np.ndarray]:
        """All close pairs within runs of one choice of blocks; ``run`` numbers them."""
        prints = rows[3].view(np.uint64)
        others = _others(plan[at_plan])
        rest = _bits_of(prints, others)
        choices = finer(run, rest, sum(n for _, n in others))
        inner = [_mask(spans) for spans in choices]
        for t, spans in enumerate(choices):
            key = (run << np.uint64(sum(n for _, n in spans))) | _bits_of(rest, spans)
            order = np.argsort(key, kind="stable")
            own, ends, far = prints[order], _run_ends(key[order]), 1
            live = np.flatnonzero(np.arange(len(own)) + 1 < ends)
            while len(live):
                for lo in range(0, len(live), memory):
                    i = live[lo : lo + memory]
                    i = i[np.bitwise_count(own[i] ^ own[i + far]) <= distance]
                    if not len(i):
                        continue
                    i, j = order[i], order[i + far]
                    unlike = sum((differing(rows[k][i], rows[k][j]).astype(np.int64) for k in range(4, 4 + CHECK_WORDS)), np.zeros(len(i), np.int64))
                    new = unlike <= check_distance
                    for before, values, upto in ((masks, prints, at_plan), (inner, rest, t)):
                        x = values[i] ^ values[j]
                        for m in before[:upto]:
                            new &= (x & m) != 0
                    if new.any():
                        yield rows[2][np.stack([i[new], j[new]], 1)]
                far += 1
                live = live[live + far < ends[live]]

    def close(rows: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Which of the pairs of rows i and j are close in both prints."""
        out = np.bitwise_count((rows[3][i] ^ rows[3][j]).view(np.uint64)) <= distance
        at = np.flatnonzero(out)
        out[at] = sum(differing(rows[k][i[at]], rows[k][j[at]]).astype(np.int64) for k in range(4, 4 + CHECK_WORDS)) <= check_distance
        return out

    def connected(run: np.ndarray, rows: np.ndarray, at_plan: int) -> Iterator[np.ndarray]:
        """Links of the connected parts within runs of one choice of blocks. Rows of one part are not compared again, so
        that many alike cost about as many comparisons, not their square."""
        others = _others(plan[at_plan])
        rest, width = _bits_of(rows[3].view(np.uint64), others), sum(n for _, n in others)
        part, some = np.arange(len(run)), min(width, 40)
        # neighbours in two orders first: what is left of large parts would mislead the choice of blocks
        for bits in (rest >> np.uint64(width - some), rest & np.uint64((1 << some) - 1)):
            order = np.argsort((run << np.uint64(some)) | bits, kind="stable")
            for far in (1, 2):
                i, j = order[:-far], order[far:]
                i, j = i[run[i] == run[j]], j[run[i] == run[j]]
                hit = close(rows, i, j)
                part = _joined(part, i[hit], j[hit])

        def arranged(key: np.ndarray):
            """Rows by key and part, where the run of each ends, and with which it is compared first: the next part's."""
            order = np.argsort(part, kind="stable")
            order = order[np.argsort(key[order], kind="stable")]
            ends, at = _run_ends(key[order]), _run_ends(key[order], part[order])
            return order, ends, at, np.flatnonzero(at < ends)

        for spans in finer(run, rest, width, part):
            key = (run << np.uint64(sum(n for _, n in spans))) | _bits_of(rest, spans)
            order, ends, at, live = arranged(key)
            found, held, done = [], 0, 0
            while len(live):
                for lo in range(0, len(live), memory):
                    i = live[lo : lo + memory]
                    i, j = order[i], order[at[i]]
                    hit = close(rows, i, j)
                    if hit.any():
                        found.append((i[hit], j[hit]))
                        held += len(found[-1][0])
                at[live] += 1
                live = live[at[live] < ends[live]]
                done += 1
                left = int((ends[live] - at[live]).sum()) if done & (done - 1) == 0 else 0
                if found and (left > SORT_COST * len(run) or held > memory or not len(live)):
                    part = _joined(part, *map(np.concatenate, zip(*found, strict=True)))
                    found, held = [], 0
                    if left > SORT_COST * len(run):
                        again = arranged(key)
                        if 2 * int((again[1] - again[2]).sum()) < left:
                            (order, ends, at, live), done = again, 0
        least = np.full(len(run), np.iinfo(np.int64).max)
        np.minimum.at(least, part, rows[2])
        own = least[part]
        other = own != rows[2]
        yield np.stack([own[other], rows[2][other]], 1)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        waiting, held, enough, found = [], 0, RUN_ROWS, []

        def flush(rows: np.ndarray) -> None:
            new = np.ones(rows.shape[1], bool)
            new[1:] = (rows[:2, 1:] != rows[:2, :-1]).any(0)
            run, which = np.cumsum(new).astype(np.uint64), (rows[0] >> 48) // SEEDS
            stops = np.append(np.flatnonzero(which[1:] != which[:-1]) + 1, len(which))
            for lo, hi in zip([0, *stops[:-1]], stops, strict=True):
                found.extend((connected if links else pairs)(run[lo:hi], rows[:, lo:hi], int(which[lo])))

        def out() -> pa.RecordBatch:
            both = np.concatenate(found) if found else np.zeros((0, 2), np.int64)
            both = np.unique(np.sort(both, 1), axis=0)
            found.clear()
            return pa.RecordBatch.from_arrays([pa.array(both[:, 0].copy()), pa.array(both[:, 1].copy())], names=["a", "b"])

        for batch in batches:
            if not batch.num_rows:
                continue
            waiting.append(np.stack([np.asarray(c) for c in batch.columns]))
            held += batch.num_rows
            if held < enough:
                continue
            rows = np.concatenate(waiting, 1)
            other = np.flatnonzero((rows[:2] != rows[:2, -1:]).any(0))
            whole = int(other[-1]) + 1 if len(other) else 0
            if whole:
                flush(rows[:, :whole])
            waiting = [rows[:, whole:].copy()]
            held = rows.shape[1] - whole
            enough = max(RUN_ROWS, 2 * held)
            if sum(map(len, found)) > 200_000:
                yield out()
        if held:
            flush(np.concatenate(waiting, 1))
        yield out()

    return kernel


def key_rows(nodes: DataFrame, count: int, distance: int = DISTANCE, most: int = CELL_ROWS) -> DataFrame:
    """(k, cell, id, f, c..): a row for each key of each node.

    Rows of a key that more than ``most`` nodes have are dealt to chunks; a cell holds two chunks, every two chunks meet
    in a cell, so that a task never needs more than ``most`` rows or so at once and no pair is lost.
    """
    # the number of the table lies above the at most 48 bits of a key
    tables = [(_key(f"f{s}", spans) + F.lit((k * SEEDS + s) << 48), f"f{s}") for s in range(SEEDS) for k, spans in enumerate(block_plan(count, distance))]
    keys = F.array(*[F.struct(key.alias("k"), F.col(f).alias("f")) for key, f in tables])
    rows = nodes.select(F.inline(keys), F.col("id").cast("long").alias("id"), *CHECK_COLS)
    cols = ["id", "f", *CHECK_COLS]
    plain = rows.select("k", F.lit(0).cast("long").alias("cell"), *cols)
    if count <= most:
        return plain
    large = nodes.select(F.explode(F.array(*[key for key, _ in tables])).alias("k")).groupBy("k").count().where(F.col("count") > most)
    large = staged(large.select("k", F.ceil(2 * F.col("count") / F.lit(most)).cast("int").alias("chunks")), "large")
    found = large.count()
    if not found:
        return plain
    both = rows.join(maybe_broadcast(large, found, 16), "k", "left").withColumn("own", F.pmod(F.xxhash64("id"), F.col("chunks")).cast("int"))
    cells = F.expr("transform(filter(sequence(0, chunks - 1), j -> j != own), j -> cast(least(j, own) as long) * chunks + greatest(j, own))")
    cell = F.explode(F.when(F.col("chunks").isNull(), F.array(F.lit(0).cast("long"))).otherwise(cells))
    return both.select("k", cell.alias("cell"), *cols)


def near_pairs(nodes: DataFrame, count: int, distance: int = DISTANCE, check_distance: int = CHECK_DISTANCE, links: bool = False) -> DataFrame:
    """Verified pairs (a < b) of nodes (id, f.., c..): exactly those within the distances in some fingerprint; with
    ``links`` only pairs that connect the same nodes, for each node at most one a key."""
    plan = block_plan(count, distance)
    tasks = max(KEY_TASKS, count * len(plan) * SEEDS // KEY_ROWS)
    rows = key_rows(nodes, count, distance).repartition(tasks, "k", "cell").sortWithinPartitions("k", "cell")
    return map_batches(rows, _verify(plan, distance, check_distance, links=links), "a long, b long").distinct()


def least_labels(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(id, label): the least id in the connected part, for each id of an edge.

    Each round joins every node to the least label around it and then jumps along labels, so rounds grow with the
    logarithm of a part's width; tables are written between rounds.
    """
    edges = staged(edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))), "edges")
    labels = staged(edges.groupBy(F.col("a").alias("id")).agg(F.least(F.min("b"), F.col("id")).alias("label")), "labels")
    for _ in range(rounds):
        near = edges.join(labels.withColumnRenamed("id", "b"), "b").groupBy(F.col("a").alias("id")).agg(F.min("label").alias("m"))
        lower = labels.join(near, "id").select("id", F.least("label", "m").alias("m"), "label")
        jump = lower.join(labels.select(F.col("id").alias("m"), F.col("label").alias("up")), "m", "left")
        new = staged(jump.select("id", F.least("m", F.coalesce("up", "m")).alias("label"), F.col("label").alias("old")), "labels")
        changed = new.where("label < old").limit(1).count()
        labels = new.select("id", "label")
        if not changed:
            return labels
    raise RuntimeError("labels did not settle")


def _groups(prints: DataFrame, distance: int, check_distance: int) -> tuple[DataFrame, DataFrame, int]:
    """From written prints (row, id, ...): (row, node) of the rows in a group of two or more, (node, best, group_size)
    of these groups, and how many rows that are. ``best`` is the row to keep: that of the least id, nulls last."""
    cols = [*PRINT_COLS, *CHECK_COLS]
    some = prints.where("words > 0")
    nodes = staged(some.groupBy(*cols).agg(F.min("row").alias("id"), F.count("*").alias("n")), "nodes")
    count = nodes.count()
    labels = least_labels(near_pairs(nodes, count, distance, check_distance, links=True))
    many = staged(nodes.join(maybe_broadcast(labels, labels.count(), 16), "id", "left").where("n > 1 or label is not null").select(*cols, F.coalesce("label", "id").alias("node")), "nodes")
    held = staged(some.select("row", "id", *cols).join(maybe_broadcast(many, many.count(), 56), cols).select("row", "id", "node"), "groups")
    best = F.min(F.struct(F.col("id").isNull().alias("none"), F.col("id"), F.col("row"))).alias("best")
    groups = held.groupBy("node").agg(best, F.count("*").alias("group_size"))
    return held.select("row", "node"), staged(groups.select("node", "best.id", "best.row", "group_size"), "groups"), held.count()


def near_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", distance: int = DISTANCE, check_distance: int = CHECK_DISTANCE) -> DataFrame:
    """A row for each document: id, ``group_id`` (least id of its group), ``group_size`` (rows) and ``is_near_copy``
    (all rows but one of each group: that of the least id, any of them if several have it).

    Documents without words (null, empty, only signs) are groups of their own. Repeated rows, and rows with one id and
    different texts, are rows of their own: each is in the group of its text. Null ids take part and sort last; a group
    of null ids only has a null ``group_id``. An empty table gives none.
    """
    ids = docs.select(F.col(id_col).alias("id"), F.monotonically_increasing_id().alias("row"), F.col(text_col).alias("text"))
    prints = staged(_printed(ids), "prints")
    held, groups, count = _groups(prints, distance, check_distance)
    member = held.join(maybe_broadcast(groups.withColumnRenamed("row", "kept").withColumnRenamed("id", "group_id"), count, 32), "node")
    out = prints.select("id", "row").join(maybe_broadcast(member, count, 40), "row", "left")
    return out.select(
        F.col("id").alias(id_col),
        F.when(F.col("kept").isNull(), F.col("id")).otherwise(F.col("group_id")).alias("group_id"),
        F.coalesce("group_size", F.lit(1).cast("long")).alias("group_size"),
        F.coalesce(F.col("row") != F.col("kept"), F.lit(False)).alias("is_near_copy"),
    )


def drop_near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", distance: int = DISTANCE, check_distance: int = CHECK_DISTANCE) -> DataFrame:
    """``docs`` with one row of each group of near copies: that of the least id, nulls last; all columns stay.

    Rows are dropped by their id where it is that of one row only; rows with a null or repeated id are written to the
    shared folder with a number of their own and dropped by that. Documents without words all stay, and an empty table
    stays empty.
    """
    AT = "__cs_at"
    ids = docs.select(F.col(id_col).alias("id"))
    again = staged(ids.groupBy("id").count().where("count > 1 or id is null").select(F.col("id").alias("__cs_id")), "repeated")
    shared = again.count()
    alone, several = docs, None
    if shared:
        twice = maybe_broadcast(again, shared, 40)
        same = F.col(id_col).eqNullSafe(F.col("__cs_id"))
        alone = docs.join(twice, same, "left_anti")
        several = staged(docs.join(twice, same, "left_semi").withColumn(AT, F.monotonically_increasing_id()), "several")
    both = alone.select(F.col(id_col).alias("id"), F.lit(None).cast("long").alias("at"), F.col(text_col).alias("text"))
    if several is not None:
        both = both.unionByName(several.select(F.col(id_col).alias("id"), F.col(AT).alias("at"), F.col(text_col).alias("text")))
    prints = staged(_printed(both.select("id", "at", F.monotonically_increasing_id().alias("row"), "text")), "prints")
    held, groups, count = _groups(prints, distance, check_distance)
    extra = held.join(maybe_broadcast(groups.select("node", F.col("row").alias("kept")), count, 16), "node").where("row != kept").select("row")
    gone = staged(prints.select("row", "id", "at").join(maybe_broadcast(extra, count, 8), "row", "left_semi").select("id", "at"), "gone")
    dropped = gone.count()
    by_id = maybe_broadcast(gone.where("at is null").select(F.col("id").alias(id_col)), dropped, 40)
    out = alone.join(by_id, id_col, "left_anti")
    if several is not None:
        by_row = maybe_broadcast(gone.where("at is not null").select(F.col("at").alias(AT)), dropped, 8)
        out = out.unionByName(several.join(by_row, AT, "left_anti").drop(AT).select(*docs.columns))
    return out.select(*docs.columns)
