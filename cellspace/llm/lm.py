"""Log-likelihood of whole documents under a gated recurrent language model, in NumPy.

Words are what blanks separate. The vocabulary holds every word that occurs as often as ``threshold`` of the number of
words says (the ``VOCAB`` most frequent at least), so it grows with the corpus, about as its root, and a model fits a
worker at any size; any other word is the unknown word followed by its bytes under a model of byte sequences counted
over all such words. The network is one gated recurrent layer; the output is factored: a softmax over groups of word
classes, one over the classes of the group (of even square-root mass, their number the root of the vocabulary), then
one over the words of the class.

Training covers every document once, in slices by hash of the text; their number grows with the root of the number of
words, and so does the number of tasks of a slice. In a round each task lays the documents of its part of the slice end
to end in lanes and runs truncated back-propagation over windows, carrying the state from window to window; the changes
of the parameters, weighted by the words of the tasks that changed them, are averaged in two levels of aggregation and
start the next round. Scoring sorts the documents of a batch by length, carries the state over
windows to the end of each, and includes the end-of-document event, so a text's length is priced too.

At scale: word counts and parameters are shuffled; texts never are.
"""

from __future__ import annotations

import math
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import count

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellspace.llm.common import map_batches, pieces, staged

VOCAB, CLASSES, HIDDEN = 2048, 40, 16
#: A word is in the vocabulary if it occurs so often, and a ``ROOT_SHARE``-th of the root of all words.
MIN_COUNT, ROOT_SHARE = 50, 8
ROUNDS, LANES, WINDOW, RATE = 2, 1024, 12, 0.1
#: Words a task trains on in a round, about; the square root of the corpus in this unit gives the rounds.
WORDS_A_TASK = 8_000_000
BLOCK_ROWS = 4096
#: Documents scored side by side.
SCORED = 1024
EDGE, UNKNOWN = 0, 1
#: Bytes before a byte that its cost may depend on.
CONTEXT, END, BEGIN = 5, 256, 257


def threshold(words: int) -> int:
    """The least count of a word of the vocabulary."""
    return max(MIN_COUNT, math.isqrt(words) // ROOT_SHARE)


def byte_grams(words: list[bytes], only_last: bool = False) -> tuple[list[np.ndarray], np.ndarray]:
    """Keys of 0, 1, 2, ... bytes of context (or of most only) for each byte and end of the words, and the lengths with
    the end.

    A key holds the symbol in its low 9 bits and the context, nearest first, above them.
    """
    lengths = np.fromiter(map(len, words), np.int64, len(words)) + 1
    flat = np.frombuffer(b"\0".join([*words, b""]), np.uint8).astype(np.int64)
    ends = np.cumsum(lengths)
    flat[ends - 1] = END
    at = np.arange(len(flat)) - np.repeat(ends - lengths, lengths)
    keys = [flat]
    for k in range(1, CONTEXT + 1):
        before = np.empty_like(flat)
        before[k:] = flat[:-k] if k < len(flat) else flat[:0]
        before[at < k] = BEGIN
        before <<= 9 * k
        before += keys[-1]
        keys.append(before)
        if only_last:
            keys = keys[-1:]
    return keys, lengths


class ByteModel:
    """-ln of bytes given those before: counts of each context length, smoothed by the next shorter one."""

    def __init__(self, byte_cost: np.ndarray, counts: list[tuple[np.ndarray, np.ndarray]]):
        self.base, self.levels = np.exp(-byte_cost), []
        for k, (keys, n) in enumerate(counts, 1):
            order = np.argsort(keys)
            keys, n = keys[order], n[order].astype(np.float64)
            context, which, kinds = np.unique(keys >> 9, return_inverse=True, return_counts=True)
            total = np.bincount(which, n, len(context)) + kinds
            left = kinds / total
            shorter = self.probability([keys & ((1 << 9 * (j + 1)) - 1) for j in range(k)])
            self.levels.append((keys, n / total[which] + left[which] * shorter, context, left))

    @staticmethod
    def _find(table: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if not len(table):
            return np.zeros(len(keys), np.int64), np.zeros(len(keys), bool)
        at = np.minimum(np.searchsorted(table, keys), len(table) - 1)
        return at, table[at] == keys

    def probability(self, keys: list[np.ndarray]) -> np.ndarray:
        """Of the last of ``keys``, each the symbol with one more byte of context."""
        k = len(keys) - 1
        if not k:
            return self.base[keys[0]]
        known, p, context, left = self.levels[k - 1]
        at, found = self._find(known, keys[k])
        out = p[at] if len(p) else np.zeros(len(at))
        if not found.all():
            new = np.flatnonzero(~found)
            shorter = self.probability([x[new] for x in keys[:k]])
            at, found = self._find(context, keys[k][new] >> 9)
            out[new] = shorter * np.where(found, left[at], 1.0) if len(left) else shorter
        return out

    def costs(self, words: list[bytes]) -> np.ndarray:
        """-ln of each whole word, its end included."""
        if not words:
            return np.zeros(0)
        keys, lengths = byte_grams(words, True)
        k = len(self.levels)
        deepest = keys[0] & ((1 << 9 * (k + 1)) - 1)
        own, which = np.unique(deepest, return_inverse=True)  # in order, so that neighbours are looked up together
        cost = -np.log(self.probability([own & ((1 << 9 * (j + 1)) - 1) for j in range(k)] + [own]))
        return np.add.reduceat(cost[which], np.cumsum(lengths) - lengths)


@dataclass
class Vocabulary:
    """``words[k]`` has id ``k + 2``; counts hold all ids; ``byte_cost`` is -ln of each byte and, last, of the end;
    ``grams`` are the keys and counts of each context length."""

    words: list[bytes]
    counts: np.ndarray
    byte_cost: np.ndarray
    grams: list[tuple[np.ndarray, np.ndarray]] = field(default_factory=list)

    def __post_init__(self):
        classes = max(CLASSES, math.isqrt(len(self.counts)))
        mass = np.cumsum(np.sqrt(self.counts.astype(np.float64)))
        order = np.minimum((mass - 1e-9) / max(mass[-1], 1e-9) * classes, classes - 1).astype(np.int64)
        self.class_of = np.unique(order, return_inverse=True)[1]
        self.starts = np.concatenate([np.flatnonzero(np.diff(self.class_of, prepend=-1)), [len(order)]])
        # groups of classes of even mass; each class is in one
        own = np.sqrt(np.bincount(self.class_of, self.counts.astype(np.float64)))
        groups, mass = math.isqrt(len(own)), np.cumsum(own)
        group = np.minimum((mass - 1e-9) / max(mass[-1], 1e-9) * groups, groups - 1).astype(np.int64)
        self.group_of = np.unique(group, return_inverse=True)[1]
        self.group_starts = np.concatenate([np.flatnonzero(np.diff(self.group_of, prepend=-1)), [len(own)]])
        self.ids = {w: k + 2 for k, w in enumerate(self.words)}
        self.bytes = ByteModel(self.byte_cost, self.grams)

    def without_words(self) -> Vocabulary:
        """What the network needs: counts and classes."""
        return Vocabulary([], self.counts, self.byte_cost)

    def spelling(self, words: list[bytes]) -> np.ndarray:
        """-ln of the bytes of each unknown word."""
        return self.bytes.costs(words)


class WordCodes:
    """Ids of words, and what the bytes of the unknown ones cost: one look-up a word for both. Unknown words met are kept
    over calls and forgotten beyond ``limit``."""

    def __init__(self, vocabulary: Vocabulary, limit: int = 300_000):
        self.v, self.size, self.limit = vocabulary, len(vocabulary.counts), limit
        self._begin()

    def _begin(self) -> None:
        # an unknown word gets its number, after those of the vocabulary, by being looked up
        self.numbers, self.costs = defaultdict(count(self.size).__next__, self.v.ids), np.zeros(0)

    def __call__(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(id of each word, which are unknown, cost of each of these)."""
        if len(self.costs) > self.limit:
            self._begin()
        known = self.size + len(self.costs)
        codes = np.fromiter(map(self.numbers.__getitem__, words), np.int64, len(words))
        late = np.flatnonzero(codes >= known)
        if len(late):
            first = late[np.diff(np.maximum.accumulate(codes[late]), prepend=known - 1) > 0]
            self.costs = np.concatenate([self.costs, self.v.spelling([words[k] for k in first.tolist()])])
        unknown = codes >= self.size
        return np.where(unknown, UNKNOWN, codes), unknown, self.costs[codes[unknown] - self.size]


def split_words(texts: pa.Array) -> tuple[pa.Array, np.ndarray]:
    """The words of all texts as bytes, one after the other, and how many each text has; a null text has none."""
    lists = pc.ascii_split_whitespace(pc.fill_null(texts, ""))
    words, counts = lists.flatten().cast(pa.binary()), np.array(pc.list_value_length(lists), np.int64)
    empty = np.asarray(pc.binary_length(words)) == 0  # beside blanks at either end
    if empty.any():
        counts -= np.bincount(np.repeat(np.arange(len(counts)), counts)[empty], minlength=len(counts))
        words = words.filter(pa.array(~empty))
    return words, counts


def count_grams(rare: DataFrame) -> list[tuple[np.ndarray, np.ndarray]]:
    """Byte sequences of the words (word, n), by context length."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            keys, lengths = byte_grams(batch.column(0).to_pylist())
            n = np.repeat(np.asarray(batch.column(1)), lengths)
            for k in range(1, CONTEXT + 1):
                own, which = np.unique(keys[k], return_inverse=True)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(own), k, np.int32)), pa.array(own), pa.array(np.bincount(which, n).astype(np.int64))], names=["level", "key", "n"])

    sums = map_batches(rare, kernel, "level int, key long, n long").groupBy("level", "key").agg(F.sum("n").alias("n")).toArrow()
    level, key, n = (np.asarray(sums[c].combine_chunks()) for c in ("level", "key", "n"))
    return [(key[level == k], n[level == k]) for k in range(1, CONTEXT + 1)]


def count_words(docs: DataFrame, text_col: str = "text", size: int = VOCAB, least: int | None = None) -> Vocabulary:
    """Counts of all words of all documents; bytes are counted under keys that begin with a blank.

    The vocabulary holds the words that occur ``least`` times (by default ``threshold`` of the number of words), and
    ``size - 2`` at least.
    """

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        octets, docs_seen, seen, rows = np.zeros(256, np.int64), 0, [], 0

        def merged() -> pa.Table:
            return pa.concat_tables(seen).group_by("word").aggregate([("n", "sum")]).select(["word", "n_sum"]).rename_columns(["word", "n"])

        def out(table: pa.Table) -> Iterator[pa.RecordBatch]:
            for batch in table.to_batches():
                lengths = np.asarray(pc.binary_length(batch.column(0)))
                flat = np.frombuffer(b"".join(batch.column(0).to_pylist()), np.uint8)
                octets[:] += np.bincount(flat, np.repeat(np.asarray(batch.column(1)), lengths), 256).astype(np.int64)
                yield batch

        for part, _ in pieces(batches, 0):
            found = split_words(part.column(0))[0].value_counts()
            docs_seen += part.num_rows - part.column(0).null_count
            seen.append(pa.table({"word": found.field("values"), "n": found.field("counts")}))
            rows += len(found)
            if rows > 1_000_000:
                seen = [merged()]
                rows = seen[0].num_rows
                if rows > 500_000:
                    yield from out(seen[0])
                    seen, rows = [], 0
        if seen:
            yield from out(merged())
        own = {b" " + bytes([k]): int(n) for k, n in enumerate(octets) if n} | {b" docs": docs_seen}
        yield pa.RecordBatch.from_arrays([pa.array(list(own), pa.binary()), pa.array(list(own.values()), pa.int64())], names=["word", "n"])

    counts = staged(map_batches(docs.select(text_col), kernel, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n")), "words")
    special = F.substring("word", 1, 1) == F.lit(b" ")
    own = {bytes(r["word"]): r["n"] for r in counts.where(special).collect()}
    total = counts.where(~special).agg(F.sum("n")).first()[0] or 0
    least = threshold(total) if least is None else least
    frequent = counts.where(~special & (F.col("n") >= least))
    if frequent.count() >= size - 2:
        found = frequent.toArrow()
        top = sorted(zip(found["word"].to_pylist(), found["n"].to_pylist(), strict=True), key=lambda r: (-r[1], r[0]))
    else:
        top = [(bytes(r["word"]), r["n"]) for r in counts.where(~special).orderBy(F.desc("n"), "word").limit(size - 2).collect()]
    rare = counts.where(~special)
    if top:
        word, n = top[-1]
        rare = rare.where((F.col("n") < n) | ((F.col("n") == n) & (F.col("word") > F.lit(bytearray(word)))))
    n = [k for _, k in top]
    octets = np.array([own.get(b" " + bytes([k]), 0) for k in range(256)] + [total], np.float64) + 0.1
    return Vocabulary([w for w, _ in top], np.array([own.get(b" docs", 0) + 1, total - sum(n) + 1, *n], np.int64), -np.log(octets / octets.sum()).astype(np.float64), count_grams(rare))


class RecurrentModel:
    """Parameters: ``gates`` [ids, 3H] (input of update, reset and candidate), ``state`` [H, 3H], ``to_group`` [H+1, G],
    ``to_class`` [C, H+1], ``to_word`` [ids, H+1]."""

    NAMES = ("gates", "state", "to_group", "to_class", "to_word")

    def __init__(self, vocabulary: Vocabulary, hidden: int = HIDDEN, seed: int = 1, params: dict[str, np.ndarray] | None = None):
        self.v, self.hidden = vocabulary, hidden
        n, c, g = len(vocabulary.counts), len(vocabulary.starts) - 1, len(vocabulary.group_starts) - 1
        if params is None:
            rng = np.random.default_rng(seed)
            make = lambda *s: (rng.standard_normal(s) * 0.1).astype(np.float32)
            params = {"gates": make(n, 3 * hidden), "state": make(hidden, 3 * hidden), "to_group": make(hidden + 1, g), "to_class": make(c, hidden + 1) * np.float32(0.3), "to_word": make(n, hidden + 1) * np.float32(0.3)}
            share = vocabulary.counts / vocabulary.counts.sum()
            mass = np.bincount(vocabulary.class_of, share)
            above = np.bincount(vocabulary.group_of, mass)
            params["to_group"][-1] = np.log(above)
            params["to_class"][:, -1] = np.log(mass / above[vocabulary.group_of])
            params["to_word"][:, -1] = np.log(share / mass[vocabulary.class_of])
        self.p = params
        self.squares = {k: np.full_like(x, 1e-3) for k, x in params.items()}

    def step_weights(self) -> list[np.ndarray]:
        """``gates`` and ``state`` with update, reset and candidate one after the other, so that all arrays of a step are
        in one piece, the first two halved: a logistic is a tanh of half its argument."""
        out = [self.p[k].reshape(-1, 3, self.hidden).swapaxes(0, 1).copy() for k in ("gates", "state")]
        for x in out:
            x[:2] *= 0.5
        return out

    def steps(self, ids: np.ndarray, h: np.ndarray, reset: np.ndarray | None = None, running: list[int] | None = None, keep: bool = False, weights: list[np.ndarray] | None = None):
        """States after each input [time, lane, H]. ``reset`` marks inputs before which the state is cleared; only the
        first ``running[t]`` lanes go on at time t; ``weights`` are those of ``step_weights``, if at hand."""
        T, B = ids.shape
        H = self.hidden
        gates, U = self.step_weights() if weights is None else weights
        out = np.zeros((T, B, H), np.float32)
        saved = []
        stay = None if reset is None else (~reset)[:, :, None].astype(np.float32)
        for t in range(T):
            b = B if running is None else running[t]
            h = h[:b]
            if stay is not None:
                h = h * stay[t, :b]
            g, u = gates.take(ids[t, :b], 1), np.matmul(h, U)
            zr = g[:2]
            zr += u[:2]
            np.tanh(zr, out=zr)
            zr += 1
            zr *= np.float32(0.5)
            z, r = zr
            c = r * u[2]
            c += g[2]
            np.tanh(c, out=c)
            new = h - c
            new *= z
            new += c
            if keep:
                saved.append((h, z, r, c, u[2]))
            out[t, :b] = h = new
        return out, saved

    def grouped(self, ids: np.ndarray) -> np.ndarray:
        """The order that brings equal ids together; 16-bit numbers are sorted digit by digit."""
        return np.argsort(ids.astype(np.uint16) if len(self.p["gates"]) <= 1 << 16 else ids, kind="stable")

    def output(self, h: np.ndarray, target: np.ndarray, grads: dict | None = None):
        """-ln p of each target given states [n, H]; with ``grads`` also the gradient of the states. Those of
        ``to_class`` and ``to_word`` are listed by runs of rows."""
        v, top = self.v, self.p["to_group"]
        n = len(target)
        ext = np.concatenate([h, np.ones((n, 1), np.float32)], 1)
        order = self.grouped(target)  # words lie by class, classes by group
        ext, target = ext[order], target[order]
        cls = v.class_of[target]
        group = v.group_of[cls]
        logit = ext @ top
        np.minimum(logit, 60, out=logit)  # weights are small: no shift is needed before exp
        rows = np.arange(n)
        cost = -logit[rows, group]
        e = np.exp(logit, out=logit)
        s = e.sum(1)
        cost += np.log(s)
        dext = None
        if grads is not None:
            e /= s[:, None]
            e[rows, group] -= 1
            grads["to_group"] += ext.T @ e
            dext = e @ top.T
        self._within("to_class", ext, cls, group, v.group_starts, cost, dext, grads)
        self._within("to_word", ext, target, cls, v.starts, cost, dext, grads)
        back = np.empty(n, np.int64)
        back[order] = rows
        return (cost[back], dext[back, :-1]) if grads is not None else cost[back]

    def _within(self, name: str, ext: np.ndarray, target: np.ndarray, run: np.ndarray, starts: np.ndarray, cost: np.ndarray, dext: np.ndarray | None, grads: dict | None) -> None:
        """Adds the softmax of each target among the parameter rows of its run; rows come in the order of runs."""
        W = self.p[name]
        edges = np.searchsorted(run, np.arange(len(starts))).tolist()
        bounds = starts.tolist()
        rows = np.arange(len(run))
        sums, picked = np.ones(len(run), np.float32), np.zeros(len(run), np.float32)
        used = np.flatnonzero((np.diff(starts) > 1) & (np.diff(edges) > 0)).tolist()
        change = None if grads is None else np.zeros_like(W)
        high = np.abs(W).sum(1).max() * max(1, -ext.min(), ext.max()) > 60  # else no logit needs a bound
        for k in used:
            a, b, lo, hi = edges[k], edges[k + 1], bounds[k], bounds[k + 1]
            x = ext[a:b]
            logit = x @ W[lo:hi].T
            if high:
                np.minimum(logit, 60, out=logit)
            at, right = rows[: b - a], target[a:b] - lo
            place = at * (hi - lo) + right
            picked[a:b] = logit.ravel()[place]
            e = np.exp(logit, out=logit)
            s = np.add.reduce(e, 1, out=sums[a:b])
            if grads is not None:
                e.ravel()[place] -= s
                share = s[:, None]
                np.matmul(e.T, x / share, out=change[lo:hi])
                back = e @ W[lo:hi]
                back /= share
                dext[a:b] += back
        if grads is not None:
            runs = [slice(bounds[k], bounds[k + 1]) for k in used]
            if 2 * sum(r.stop - r.start for r in runs) > len(W):  # rows without a change stay as they are
                runs = [slice(None)]
            grads[name] += [(r, change[r]) for r in runs]
        cost -= picked
        cost += np.log(sums)

    def window(self, ids: np.ndarray, target: np.ndarray, h: np.ndarray) -> tuple[float, np.ndarray, dict[str, np.ndarray]]:
        """Cost of a window [time, lane], the state after it and the gradients, cut off at its beginning."""
        cost, h, parts = self.window_parts(ids, target, h)
        grads = {k: np.zeros_like(x) for k, x in self.p.items()}
        for k, some in parts.items():
            for rows, g in some:
                grads[k][rows] = g
        return cost, h, grads

    def window_parts(self, ids: np.ndarray, target: np.ndarray, h: np.ndarray) -> tuple[float, np.ndarray, dict[str, list]]:
        """The same with gradients as (rows, values), only of the rows that the window uses."""
        H = self.hidden
        back = np.ascontiguousarray(self.p["state"].reshape(H, 3, H).transpose(1, 2, 0))
        grads = {"state": np.zeros((3, H, H), np.float32), "to_group": np.zeros_like(self.p["to_group"]), "to_class": [], "to_word": []}
        reset = ids == EDGE
        out, saved = self.steps(ids, h, reset, keep=True)
        T, B = ids.shape
        cost, dout = self.output(out.reshape(T * B, H), target.ravel(), grads)
        dout = dout.reshape(T, B, H)
        dg, dh = np.empty((T, B, 3, H), np.float32), np.zeros((B, H), np.float32)
        stay, du = (~reset)[:, :, None].astype(np.float32), np.empty((3, B, H), np.float32)
        for t in range(T - 1, -1, -1):
            before, z, r, c, uc = saved[t]
            d = dout[t] + dh
            not_z, dz = 1 - z, before - c
            dc = c * c
            np.subtract(1, dc, out=dc)
            dc *= not_z
            dc *= d
            dz *= d
            dz *= z
            np.multiply(dz, not_z, out=du[0])
            dr = 1 - r
            dr *= r
            dr *= uc
            np.multiply(dr, dc, out=du[1])
            np.multiply(dc, r, out=du[2])
            dg[t, :, 0], dg[t, :, 1], dg[t, :, 2] = du[0], du[1], dc
            grads["state"] += np.matmul(before.T, du)
            dh = np.matmul(du, back).sum(0)
            d *= z
            dh += d
            dh *= stay[t]
        flat, dg = ids.ravel(), dg.reshape(T * B, 3 * H)
        strange = flat == UNKNOWN  # up to half of all
        gates = [(np.array([UNKNOWN]), (strange.astype(np.float32) @ dg)[None])] if strange.any() else []
        rest = np.flatnonzero(~strange)
        if len(rest):
            order = rest[self.grouped(flat[rest])]
            first = np.flatnonzero(np.diff(flat[order], prepend=-1))
            gates.append((flat[order][first], np.add.reduceat(dg[order], first, axis=0)))
        every = slice(None)
        return float(cost.sum()), out[-1], {"gates": gates, "state": [(every, grads["state"].swapaxes(0, 1).reshape(H, 3 * H))], "to_group": [(every, grads["to_group"])], "to_class": grads["to_class"], "to_word": grads["to_word"]}

    def update(self, grads: dict[str, list], scale: float, rate: float = RATE) -> None:
        for k, some in grads.items():
            for rows, g in some:
                g *= np.float32(scale)
                squares = self.squares[k][rows]
                squares += g * g
                if not isinstance(rows, slice):
                    self.squares[k][rows] = squares
                g *= np.float32(rate)
                g /= np.sqrt(squares)
                self.p[k][rows] -= g

    def train_stream(self, stream: np.ndarray, lanes: int = LANES, window: int = WINDOW) -> float:
        """One pass over documents laid end to end, each begun by the edge id; the mean cost of a word. What doesn't
        fill the lanes evenly follows in fewer lanes, so every word is a target once."""
        at, words, total = 0, len(stream) - 1, 0.0
        while (n := words - at) > 0:
            lanes = max(1, min(lanes, n // (2 * window)))
            length = n // lanes
            ids = stream[at : at + lanes * length].reshape(lanes, length).T
            target = stream[at + 1 : at + lanes * length + 1].reshape(lanes, length).T
            h = np.zeros((lanes, self.hidden), np.float32)
            for t in range(0, length, window):
                x, y = ids[t : t + window], target[t : t + window]
                cost, h, grads = self.window_parts(x, y, h)
                self.update(grads, 1000.0 / max(x.size, 1000))
                total += cost
            at += lanes * length
        return total / max(words, 1)

    def log_likelihoods(self, docs: list[np.ndarray], window: int = 64, lanes: int = SCORED) -> np.ndarray:
        """ln p of each whole document, its end included; the state is carried over windows. Documents go by length,
        ``lanes`` at a time, which is what a processor's cache holds."""
        order = np.argsort([-len(d) for d in docs], kind="stable")
        weights, result = self.step_weights(), np.empty(len(docs))
        for at in range(0, len(docs), lanes):
            some = order[at : at + lanes]
            result[some] = self._falling([docs[k] for k in some], window, weights)
        return result

    def _falling(self, docs: list[np.ndarray], window: int, weights: list[np.ndarray]) -> np.ndarray:
        """The same of documents whose lengths fall."""
        sizes = np.array([len(d) + 1 for d in docs])
        starts = np.concatenate([[0], np.cumsum(sizes)[:-1]])
        flat = stream_of(docs)
        total = np.zeros(len(docs))
        h = np.zeros((len(docs), self.hidden), np.float32)
        for t0 in range(0, int(sizes[0]), window):
            B = int(np.searchsorted(-sizes, -t0, "left"))
            T = min(window, int(sizes[0]) - t0)
            running = [int(np.searchsorted(-sizes, -(t0 + t), "left")) for t in range(T)]
            where = np.minimum(starts[:B] + t0 + np.arange(T)[:, None], len(flat) - 2)
            out, _ = self.steps(flat[where], h[:B], running=running, weights=weights)
            live = np.arange(B) < np.array(running)[:, None]
            t, lane = np.nonzero(live)
            target = flat[where[live] + 1]
            cost = self.output(out[live], target)
            total[:B] -= np.bincount(lane, cost, B)
            h = out[-1][: running[-1]]
        return total


def stream_of(docs: list[np.ndarray]) -> np.ndarray:
    """Each document after an edge, and an edge at the end."""
    lengths = np.array([len(d) + 1 for d in docs], np.int64)
    out = np.empty(int(lengths.sum()) + 1, np.int32)
    edges = np.concatenate([[0], np.cumsum(lengths)])
    out[edges] = EDGE
    inner = np.ones(len(out), bool)
    inner[edges] = False
    out[inner] = np.concatenate(docs) if docs else []
    return out


def encoded_docs(docs: DataFrame, v: Vocabulary, id_col: str, text_col: str) -> DataFrame:
    """(id, ids, words, unknown, spelled, bytes) in the shared folder: what training and scoring read. Ids are 16-bit
    (32-bit for larger vocabularies); ``spelled`` is the cost of the unknown words' bytes. Null texts have nulls."""
    df = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    sent = df.sparkSession.sparkContext.broadcast(v)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = sent.value
        kind = id_type(len(vocabulary.counts))
        codes = WordCodes(vocabulary)
        for part, _ in pieces(batches, 1, 1_500_000):
            words, counts = split_words(part.column(1))
            found = words.dictionary_encode()  # each different word of a piece is looked up once
            which, n = np.asarray(found.indices), len(found.dictionary)
            own, strange, cost = codes(found.dictionary.to_pylist())
            costs = np.zeros(n)
            costs[strange] = cost
            owner, docs = np.repeat(np.arange(part.num_rows), counts), part.num_rows
            ids, ends, none = own.astype(kind)[which], np.cumsum(counts), np.asarray(part.column(1).is_null())
            size = np.bincount(owner, np.asarray(pc.binary_length(words)), docs).astype(np.int64) + counts
            unknown = np.bincount(owner, strange[which], docs).astype(np.int32)
            raw = [None if no else ids[a:b].tobytes() for no, a, b in zip(none, ends - counts, ends, strict=True)]
            cols = [pa.array(raw, pa.binary()), pa.array(counts.astype(np.int32), mask=none), pa.array(unknown, mask=none), pa.array(np.bincount(owner, costs[which], docs).astype(np.float64), mask=none), pa.array(size, mask=none)]
            yield pa.RecordBatch.from_arrays([part.column(0), *cols], names=["id", "ids", "words", "unknown", "spelled", "bytes"])

    out = staged(map_batches(df, kernel, f"id {df.schema['id'].dataType.simpleString()}, ids binary, words int, unknown int, spelled double, bytes long"), "word-ids")
    sent.destroy()
    return out


def id_type(size: int) -> type:
    return np.uint16 if size <= 1 << 16 else np.int32


def _changes(kind: int, new: np.ndarray, old: np.ndarray, words: int) -> Iterator[pa.RecordBatch]:
    """The rows that training changed, in blocks: row numbers, weights and weighted changes."""
    rows = np.flatnonzero((new != old).any(1))
    for part in np.split(rows, np.flatnonzero(np.diff(rows // BLOCK_ROWS)) + 1):
        if len(part):
            yield _block(kind, int(part[0]) // BLOCK_ROWS, part % BLOCK_ROWS, np.full(len(part), words, np.float64), (new[part].astype(np.float64) - old[part]) * words)


def _block(kind: int, block: int, rows: np.ndarray, weight: np.ndarray, body: np.ndarray) -> pa.RecordBatch:
    raw = [rows.astype(np.int32).tobytes(), weight.astype(np.float32).tobytes(), body.astype(np.float32).tobytes()]
    return pa.RecordBatch.from_arrays([pa.array([kind], pa.int32()), pa.array([block], pa.int32()), *(pa.array([x], pa.binary()) for x in raw)], names=["kind", "block", "rows", "weight", "body"])


def _opened(r: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    rows = np.frombuffer(r["rows"], np.int32)
    return rows, np.frombuffer(r["weight"], np.float32), np.frombuffer(r["body"], np.float32).reshape(len(rows), -1)


def _summed(table: pa.Table) -> pa.Table:
    """Adds the changes of one block."""
    weight, body, found = np.zeros(BLOCK_ROWS), None, table.select(["kind", "block", "rows", "weight", "body"]).to_pylist()
    for r in found:
        rows, w, x = _opened(r)
        if body is None:
            body = np.zeros((BLOCK_ROWS, x.shape[1]))
        weight[rows] += w
        body[rows] += x
    rows = np.flatnonzero(weight)
    return pa.Table.from_batches([_block(found[0]["kind"], found[0]["block"], rows, weight[rows], body[rows])])


def train_round(coded: DataFrame, model: RecurrentModel, slice_no: int, rounds: int, tasks: int | None = None) -> RecurrentModel:
    """Every task trains on its part of the slice from the same parameters; the weighted mean of each row over the tasks
    that changed it comes back."""
    spark = coded.sparkSession
    sent = spark.sparkContext.broadcast((model.v, model.p, model.hidden))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v, params, hidden = sent.value
        mine = RecurrentModel(v, hidden, params={k: x.copy() for k, x in params.items()})
        kind, words, waiting, size = id_type(len(v.counts)), 0, [], 0
        for batch in batches:
            for raw in batch.column(0):
                waiting.append(np.frombuffer(raw.as_py(), kind))
                size += len(waiting[-1]) + 1
                if size > 2_000_000:
                    mine.train_stream(stream_of(waiting))
                    words, waiting, size = words + size, [], 0
        if size:
            mine.train_stream(stream_of(waiting))
            words += size
        if words:
            for k, name in enumerate(RecurrentModel.NAMES):
                yield from _changes(k, mine.p[name], params[name], words)

    mine = F.pmod(F.xxhash64("ids"), F.lit(rounds)) == slice_no
    part = coded.select("ids").where(F.col("ids").isNotNull() & mine)
    schema = "kind int, block int, rows binary, weight binary, body binary"
    sums = map_batches(part.coalesce(tasks) if tasks else part, kernel, schema)
    sums = sums.withColumn("salt", F.floor(F.spark_partition_id() / 16))
    sums = sums.groupBy("kind", "block", "salt").applyInArrow(_summed, schema)
    rows = sums.groupBy("kind", "block").applyInArrow(_summed, schema).collect()  # the size of the model
    sent.destroy()
    params = {k: x.copy() for k, x in model.p.items()}
    for r in rows:
        at, weight, body = _opened(r)
        params[RecurrentModel.NAMES[r["kind"]]][r["block"] * BLOCK_ROWS + at] += body / weight[:, None]
    return RecurrentModel(model.v, model.hidden, params=params)


def rounds_of(words: int, least: int = ROUNDS) -> int:
    return max(least, math.ceil(math.sqrt(words / WORDS_A_TASK)))


def lm_log_likelihood(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocab: int = VOCAB, hidden: int = HIDDEN, rounds: int = ROUNDS) -> DataFrame:
    """Trains on all documents and scores them all: see ``lm_scores``. ``vocab`` and ``rounds`` are the least numbers;
    both follow the corpus beyond."""
    v = count_words(docs, text_col, vocab)
    coded = encoded_docs(docs, v, id_col, text_col)
    v = v.without_words()
    model = RecurrentModel(v, hidden)
    words = int(v.counts.sum())
    rounds = rounds_of(words, rounds)
    tasks = math.ceil(words / rounds / WORDS_A_TASK)
    for k in range(rounds):
        model = train_round(coded, model, k, rounds, tasks)
    return lm_scores(coded, model).withColumnRenamed("id", id_col)


def lm_scores(coded: DataFrame, model: RecurrentModel) -> DataFrame:
    """(id, words, unknown, log_likelihood, bits_per_byte) of each whole document.

    A null text gives nulls. An empty or blank text has 0 words, the log-likelihood of ending at once and a null
    bits_per_byte. Null ids stay null; repeated rows repeat.
    """
    spark: SparkSession = coded.sparkSession
    sent = spark.sparkContext.broadcast((model.v, model.p, model.hidden))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v, params, hidden = sent.value
        m, kind = RecurrentModel(v, hidden, params=params), id_type(len(v.counts))
        for batch in batches:
            raw = batch.column(1).to_pylist()
            log_p = m.log_likelihoods([np.frombuffer(x or b"", kind) for x in raw])
            spelled, size = (np.array([x or 0 for x in batch.column(k).to_pylist()], np.float64) for k in (4, 5))
            p = log_p - spelled
            none = np.array([x is None for x in raw])
            bits = -p / np.log(2) / np.maximum(size, 1)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), batch.column(3), pa.array(np.round(p, 4), mask=none), pa.array(np.round(bits, 6), mask=none | (size == 0))], names=["id", "words", "unknown", "log_likelihood", "bits_per_byte"])

    return map_batches(coded, kernel, f"id {coded.schema['id'].dataType.simpleString()}, words int, unknown int, log_likelihood double, bits_per_byte double")
