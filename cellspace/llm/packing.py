"""Best-fit packing of documents into sequences, in bulk-synchronous rounds.

A document takes as many places as its text has tokens; one longer than a sequence is cut into full sequences and a
rest, so nothing is lost. Rests and short documents are items. Items are range-sorted by size (equal sizes by hash)
into homes of about ``HOME_ITEMS``. In each round the open gaps are sorted too and matched with the homes' unplaced
volume by successor: from the largest sizes down, each home is given the smallest gaps that are no smaller than its
items; gaps of equal size are told apart by rank. Each home then sweeps its items from large to small, putting each
into the smallest gap that takes it and updating that gap. Rounds repeat with what is left, until nothing is. When no
gap fits, the homes with the larger half of the volume open sequences, whose gaps the smaller items see in the next
round; items over half a sequence open theirs at once, as no two of them share one.

The driver sees a histogram of gaps (at most ``capacity`` rows) and one row for each home, and gives back runs of ranks.
What is shuffled is a few numbers for each item.
"""

from __future__ import annotations

from bisect import bisect_left, insort

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_type
from pyspark.sql.window import Window

from cellspace.llm.bpe import bpe_encode, token_counts
from cellspace.llm.common import maybe_broadcast, staged, tokenizer_path

#: Places of a sequence, in tokens.
CAPACITY = 2048
VOCABULARY = tokenizer_path("byte_bpe_50k.tiktoken")
HOME_ITEMS = 50_000


def sweep(sizes: list[int], gaps: list[int], capacity: int, may_open: bool) -> tuple[list[tuple[int, int]], list[int]]:
    """Best fit of sizes (falling) into gaps (by index), opening new ones if allowed or if over half a sequence.

    Gives (gap index or -1, offset) of each size, and all gaps as they are after it; new ones follow the given ones.
    """
    left = list(gaps)
    order = sorted((g, k) for k, g in enumerate(left) if g)
    out = []
    for s in sizes:
        at = bisect_left(order, (s, -1))
        if at < len(order):
            g, k = order.pop(at)
        elif may_open or 2 * s > capacity:
            g, k = capacity, len(left)
            left.append(capacity)
        else:
            out.append((-1, 0))
            continue
        out.append((k, capacity - g))
        left[k] = g - s
        if left[k]:
            insort(order, (left[k], k))
    return out, left


def assign_gaps(histogram: dict[int, int], volumes: list[tuple[int, int, int, int]]) -> list[tuple[int, int, int, int]]:
    """(gap, first rank, end rank, home) from gaps by size and (home, least size, greatest size, volume) of homes.

    Homes are served from large to small; a home takes the smallest gaps that fit all of its items, then those that fit
    some, until their sum reaches its volume.
    """
    free, taken = dict(histogram), dict.fromkeys(histogram, 0)
    classes = sorted(g for g in free if g)
    out = []
    for home, least, greatest, volume in sorted(volumes, key=lambda v: -v[2]):
        a, b = bisect_left(classes, greatest), bisect_left(classes, least)
        for g in [*classes[a:], *reversed(classes[b:a])]:
            if volume <= 0:
                break
            if free[g] and (n := min(free[g], -(-volume // g))):
                out.append((g, taken[g], taken[g] + n, home))
                taken[g] += n
                free[g] -= n
                volume -= n * g
    return out


def best_fit_pack(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", capacity: int = CAPACITY, home_items: int = HOME_ITEMS, vocabulary: str = VOCABULARY) -> DataFrame:
    """(id, piece, bin_id, start, length): where each piece of each document lies, in tokens. Piece k holds the tokens
    from ``k * capacity`` on.

    Null and empty texts take no place: one row with piece 0, a null bin, start null and length 0. Null ids are packed
    as any other, of any type; repeated rows are packed each. An empty table gives none.
    """
    counted = token_counts(docs, id_col, text_col, vocabulary).select("id", F.col("tokens").alias("n"))
    # row: tells equal ids apart; only its value within one written table matters
    sized = staged(counted.withColumn("row", F.monotonically_increasing_id()), "sizes")
    return _packed(sized, capacity, home_items).drop("row").withColumnRenamed("id", id_col)


def packed_sequences(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", capacity: int = CAPACITY, home_items: int = HOME_ITEMS, vocabulary: str = VOCABULARY) -> DataFrame:
    """(bin_id, tokens, ids, lengths): the sequences themselves, with the documents they hold in order and how many
    tokens of each. Documents without tokens are in none."""
    coded = bpe_encode(docs, id_col, text_col, vocabulary).select(F.col(id_col).alias("id"), "tokens")
    coded = staged(coded.withColumn("row", F.monotonically_increasing_id()), "coded")
    where = _packed(coded.select("id", F.coalesce(F.size("tokens"), F.lit(0)).cast("long").alias("n"), "row"), capacity, home_items)
    part = where.where("length > 0").join(coded.select("row", "tokens"), "row")
    part = part.select("bin_id", F.struct("start", "id", "length", F.slice("tokens", F.col("piece") * capacity + 1, F.col("length")).alias("t")).alias("p"))
    bins = part.groupBy("bin_id").agg(F.sort_array(F.collect_list("p")).alias("p"))
    return bins.select("bin_id", F.flatten(F.col("p.t")).alias("tokens"), F.col("p.id").alias("ids"), F.col("p.length").alias("lengths"))


def _packed(sized: DataFrame, capacity: int, home_items: int) -> DataFrame:
    """(id, row, piece, bin_id, start, length) from the written table (id, n, row)."""
    id_type = sized.schema["id"].dataType
    sized = sized.withColumn("n", F.greatest("n", F.lit(0)))
    whole, rest = F.floor(F.col("n") / capacity), F.col("n") % capacity
    empty = sized.where("n = 0").select("id", "row", F.lit(0).alias("piece"), F.lit(None).cast("string").alias("bin_id"), F.lit(None).cast("int").alias("start"), F.lit(0).alias("length"))
    full = sized.where(F.col("n") >= capacity).select("id", "row", F.explode(F.sequence(F.lit(0), (whole - 1).cast("int"))).alias("piece"))
    full = full.select("id", "row", "piece", F.concat_ws("-", F.lit("full"), "row", "piece").alias("bin_id"), F.lit(0).alias("start"), F.lit(capacity).alias("length"))
    items = sized.where(rest > 0).select("id", "row", whole.cast("int").alias("piece"), rest.cast("int").alias("size"))
    items = items.withColumn("key", F.col("size") * 65536 + F.pmod(F.xxhash64("row"), F.lit(65536)))
    homes = max(1, -(-items.count() // home_items))
    items = staged(items.repartitionByRange(homes, "key").select("id", "row", "piece", "size", F.spark_partition_id().alias("home")), "items")

    spark = sized.sparkSession
    out_type = T.StructType([T.StructField("kind", T.IntegerType()), T.StructField("id", id_type), T.StructField("row", T.LongType()), T.StructField("piece", T.IntegerType()), T.StructField("size", T.IntegerType()), T.StructField("home", T.IntegerType()), T.StructField("bin_id", T.StringType()), T.StructField("start", T.IntegerType())])
    nothing = {"id": F.lit(None).cast(id_type), "row": F.lit(None).cast("long"), "piece": F.lit(None).cast("int"), "bin_id": F.lit(None).cast("string"), "start": F.lit(None).cast("int")}
    placed, gaps, number, stuck = [], None, 0, False
    while True:
        state = items.select(F.lit(0).alias("kind"), "id", "row", "piece", "size", "home", nothing["bin_id"].alias("bin_id"), nothing["start"].alias("start"))
        may_open, idle, plan = set(), None, []
        volumes = [tuple(r) for r in items.groupBy("home").agg(F.min("size"), F.max("size"), F.sum("size")).collect()]
        if gaps is not None:
            histogram = {r["size"]: r["n"] for r in gaps.groupBy("size").agg(F.count("*").alias("n")).collect()}
            plan = [] if stuck else assign_gaps(histogram, volumes)
            if plan:
                ranked = gaps.withColumn("rank", F.row_number().over(Window.partitionBy("size").orderBy("bin_id")) - 1)
                table = spark.createDataFrame(plan, "g int, first long, past long, to int")
                ranked = ranked.join(maybe_broadcast(table, len(plan), 24), (F.col("size") == F.col("g")) & (F.col("rank") >= F.col("first")) & (F.col("rank") < F.col("past")), "left")
                ranked = staged(ranked.select("size", "bin_id", F.col("to").alias("home")), "gaps")
                idle = ranked.where("home is null").select("size", "bin_id")
                state = state.unionByName(ranked.where("home is not null").select(F.lit(1).alias("kind"), "size", "home", "bin_id", *[nothing[c].alias(c) for c in ("id", "row", "piece", "start")]))
            else:  # no gap fits: the homes with the larger half of the volume open sequences
                idle, total = gaps, sum(v[3] for v in volumes)
                for v in sorted(volumes, key=lambda v: -v[2]):
                    if not may_open or 2 * sum(x[3] for x in volumes if x[0] in may_open) < total:
                        may_open.add(v[0])
        done = staged(state.groupBy("home").applyInArrow(_home_kernel(capacity, may_open, number, to_arrow_type(id_type)), out_type), "round")
        placed.append(done.where("kind = 2"))
        items = done.where("kind = 0").select("id", "row", "piece", "size", "home")
        gaps = done.where("kind = 1").select("size", "bin_id")
        if idle is not None:
            gaps = gaps.unionByName(idle)
        counts = {r["kind"]: r["count"] for r in done.groupBy("kind").count().collect()}
        if not counts.get(0):
            break
        stuck = bool(number) and not counts.get(2)
        number += 1
    found = empty.unionByName(full)
    for p in placed:
        found = found.unionByName(p.select("id", "row", "piece", "bin_id", "start", F.col("size").alias("length")))
    return found


def _home_kernel(capacity: int, may_open: set[int], number: int, id_type: pa.DataType):
    """Rows in: items (kind 0) and gaps (kind 1) of a home. Rows out: unplaced items (0), gaps (1), placed items (2)."""
    names = ["kind", "id", "row", "piece", "size", "home", "bin_id", "start"]
    types = [pa.int32(), id_type, pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.string(), pa.int32()]

    def kernel(table: pa.Table) -> pa.Table:
        rows = list(zip(*(table[n].to_pylist() for n in names), strict=True))
        items = sorted((r for r in rows if r[0] == 0), key=lambda r: (-r[4], r[2], r[3]))
        gaps = sorted((r for r in rows if r[0] == 1), key=lambda r: (r[4], r[6]))
        home = rows[0][5]
        where, left = sweep([r[4] for r in items], [r[4] for r in gaps], capacity, home in may_open)
        bins = [r[6] for r in gaps]
        bins += [f"{number}-{home}-{k}" for k in range(len(left) - len(bins))]
        out = [(2 if k >= 0 else 0, r[1], r[2], r[3], r[4], home, bins[k] if k >= 0 else None, at if k >= 0 else None) for r, (k, at) in zip(items, where, strict=True)]
        out += [(1, None, None, None, g, home, b, None) for g, b in zip(left, bins, strict=True) if g]
        cols = list(zip(*out, strict=True)) if out else [[]] * 8
        return pa.table([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names=names)

    return kernel
