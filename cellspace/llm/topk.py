"""Exact nearest neighbours of every vector, or of chosen ones among all, by multi-resolution segment statistics.

A vector is cut into 1, 2, 4, ... segments; each segment keeps its mean and deviation. The squared distance of two
vectors is at least the sum over segments of (segment length) x ((difference of means)^2 + (difference of
deviations)^2), and finer levels bound it better. Vectors are range-sorted by their coarsest statistics into blocks.
The first pass searches each block in itself, which bounds every query's k-th distance. Neighbouring blocks form groups;
a task takes one pair of groups whose boxes of statistics may hold something nearer, so a block is sent to as many tasks
as there are groups it may meet, not to each block's. The task visits its pairs of blocks that may matter, prunes pairs
of vectors level by level from coarse to fine, computes exact distances of the survivors, and tightens the bounds with
what it found. A pair of blocks is visited once and serves both sides. Rows that ask for neighbours and rows that don't
are in blocks of their own; blocks that don't ask have limits below any distance, so two of them never meet.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cellspace.llm.common import map_batches, staged
from cellspace.plans.shared import row_numbers

BLOCK = 2048
#: Most blocks of a group: a task holds two groups.
GROUP_BLOCKS = 16
TILE = 512
#: Least slack for single-precision bounds; candidates within it are settled in double precision.
SLACK = 1e-4
#: Units of rounding, of single and double precision.
SINGLE, DOUBLE = 2.0**-24, 2.0**-53


def levels_of(dim: int, finest: int = 16) -> list[int]:
    out, n = [], 1
    while n <= min(dim, finest):
        out.append(n)
        n *= 2
    return out


def statistics(x: np.ndarray, segments: int) -> np.ndarray:
    """[vectors, 2 * segments] whose squared Euclidean distances are the lower bounds of that level."""
    edges = np.linspace(0, x.shape[1], segments + 1).round().astype(int)
    cols = []
    for a, b in zip(edges, edges[1:], strict=False):
        part, root = x[:, a:b], np.sqrt(b - a)
        cols += [part.mean(1) * root, part.std(1) * root]
    return np.stack(cols, 1)


def squared(a: np.ndarray, b: np.ndarray, aa: np.ndarray, bb: np.ndarray) -> np.ndarray:
    out = a @ b.T
    out *= -2
    out += aa[:, None]
    out += bb[None, :]
    return out


class Prepared:
    """A block of vectors with its statistics in single precision, measured from ``centre``."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, centre: np.ndarray | None = None):
        self.ids, self.x = ids, x.astype(np.float64)
        near = self.x - (self.x.mean(0) if centre is None else centre)
        with np.errstate(over="ignore"):
            self.levels = [statistics(near, n).astype(np.float32) for n in levels_of(x.shape[1])] + [near.astype(np.float32)]
            self.norms = [(s * s).sum(1) for s in self.levels]
            #: what rounding may add to or take from a squared distance of two vectors, for each of both
            terms = x.shape[1] + 4
            self.slack = 4 * terms * (SINGLE * (near * near).sum(1).max(initial=0) + DOUBLE * (self.x * self.x).sum(1).max(initial=0))


def survivors(a: Prepared, b: Prepared, limit_a: np.ndarray, limit_b: np.ndarray, same: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(rows of a, rows of b) whose distance may be within the limit of either; ``limit`` is squared.

    Level by level the columns that no row of the tile can use are dropped; what is left of the last level, the vectors
    themselves, are the survivors.
    """
    slack = SLACK + a.slack + b.slack
    for at in range(0, len(a.ids), TILE):
        rows = np.arange(at, min(at + TILE, len(a.ids)))
        cols = np.arange(len(b.ids)) if not same else np.arange(at, len(b.ids))
        for level, (sa, sb) in enumerate(zip(a.levels, b.levels, strict=True)):
            d = squared(sa[rows], sb[cols], a.norms[level][rows], b.norms[level][cols])
            within = ~(d > np.maximum(limit_a[rows][:, None], limit_b[cols][None, :]) + slack)  # overflow passes
            if level + 1 < len(a.levels):
                rows, cols = rows[within.any(1)], cols[within.any(0)]
                if not len(rows) or not len(cols):
                    break
        else:
            i, j = np.nonzero(within)
            i, j = rows[i], cols[j]
            if same:
                i, j = i[j > i], j[j > i]
            if len(i):
                yield i, j


def exact(a: Prepared, b: Prepared, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    out = np.empty(len(i))
    for at in range(0, len(i), 200_000):
        d = a.x[i[at : at + 200_000]] - b.x[j[at : at + 200_000]]
        out[at : at + 200_000] = np.einsum("ij,ij->i", d, d)
    return out


def best(query: np.ndarray, other: np.ndarray, d: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The k nearest of each query by (distance, id)."""
    order = np.lexsort((other, d, query))
    query, other, d = query[order], other[order], d[order]
    first = np.flatnonzero(np.diff(query, prepend=query[:1] - 1))
    rank = np.arange(len(query)) - np.repeat(first, np.diff(np.append(first, len(query))))
    keep = rank < k
    return query[keep], other[keep], d[keep]


def own_limits(p: Prepared, k: int) -> np.ndarray:
    """An upper bound of the k-th squared distance of each vector of a block, from the block alone."""
    n = len(p.ids)
    limit = np.full(n, np.inf)
    if n > k:
        for at in range(0, n, TILE):
            d = squared(p.levels[-1][at : at + TILE], p.levels[-1], p.norms[-1][at : at + TILE], p.norms[-1])
            d[np.arange(len(d)), np.arange(at, at + len(d))] = np.inf
            limit[at : at + TILE] = np.partition(d, k - 1, axis=1)[:, k - 1] + SLACK + 2 * p.slack
    return np.where(np.isnan(limit), np.inf, limit)


_APART = "aggregate(zip_with(zip_with(a_lo, b_hi, (x, y) -> x - y), zip_with(b_lo, a_hi, (x, y) -> x - y), (x, y) -> greatest(x, y, 0.0D)), 0.0D, (s, v) -> s + v * v)"


class _Side:
    """A block in a task: prepared vectors, limits, and the best found so far."""

    def __init__(self, r: dict, dtype: type, centre: np.ndarray):
        self.no = r["no"]
        self.p = Prepared(np.frombuffer(r["ids"], np.int64), np.frombuffer(r["body"], dtype).reshape(-1, r["dim"]), centre)
        self.limit = np.frombuffer(r["limits"]).copy()
        self.lo, self.hi = np.array(r["lo"]), np.array(r["hi"])
        self.found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

    def add(self, query: np.ndarray, other: np.ndarray, d: np.ndarray, k: int) -> None:
        """Keeps the k nearest of each query and lowers the limits of those that have k."""
        near = ~(d > self.limit[query] + SLACK)
        if not near.any():
            return
        self.found.append((query[near], other[near], d[near]))
        q, o, d = best(*(np.concatenate(x) for x in zip(*self.found, strict=True)), k)
        self.found = [(q, o, d)]
        count = np.bincount(q, minlength=len(self.limit))
        last = np.cumsum(count)[count >= k] - 1
        self.limit[q[last]] = np.minimum(self.limit[q[last]], d[last] + SLACK)


def _visit(a: _Side, b: _Side, k: int) -> None:
    same = a is b
    gap = np.maximum(np.maximum(a.lo - b.hi, b.lo - a.hi), 0)
    if not same and (gap * gap).sum() > max(a.limit.max(), b.limit.max()) + SLACK:
        return
    for i, j in survivors(a.p, b.p, a.limit, b.limit, same):
        d = exact(a.p, b.p, i, j)
        if same:
            a.add(np.concatenate([i, j]), np.concatenate([a.p.ids[j], a.p.ids[i]]), np.concatenate([d, d]), k)
        else:
            a.add(i, b.p.ids[j], d, k)
            b.add(j, a.p.ids[i], d, k)


def _cell_kernel(k: int, dtype: type):
    """Rows of a cell: the blocks of two groups, or of one with itself."""

    def kernel(table: pa.Table) -> pa.Table:
        rows = table.to_pylist()
        centre = np.frombuffer(rows[0]["body"], dtype).reshape(-1, rows[0]["dim"]).astype(np.float64).mean(0)
        own = [_Side(r, dtype, centre) for r in sorted(rows, key=lambda r: r["no"])]
        side = {r["no"]: r["side"] for r in rows}
        for x, a in enumerate(own):
            for b in own[x:]:
                if side[a.no] == 2 or side[a.no] != side[b.no]:  # a group with itself, or the two sides
                    _visit(a, b, k)
        parts = [(np.full(len(f[0]), s.no), *f) for s in own for f in s.found]
        no, at, other, d = (np.concatenate(x) for x in zip(*parts, strict=True)) if parts else (np.zeros(0, np.int64),) * 3 + (np.zeros(0),)
        return pa.table([pa.array(no, pa.int64()), pa.array(at, pa.int64()), pa.array(other, pa.int64()), pa.array(d, pa.float64())], names=["no", "at", "neighbour", "d"])

    return kernel


def exact_top_k(
    vectors: DataFrame, k: int = 10, id_col: str = "vec_id", vector_col: str = "embedding", block: int = BLOCK, group_blocks: int = GROUP_BLOCKS, queries: Column | None = None
) -> DataFrame:
    """(id, rank, neighbour, distance): the ``k`` nearest other rows of every query by Euclidean distance, ties by id.

    Queries are the rows for which ``queries`` holds, all rows if it isn't given; neighbours are all rows. Ids may be of any type that can be ordered. Rows with a null id or vector, a null or
    non-finite entry or no entry take no part. Vectors of different lengths aren't compared. Repeated rows are
    neighbours of one another at distance 0. A row with fewer than k comparable others has as many neighbours as there
    are. An empty table gives none.
    """
    spark = vectors.sparkSession
    ask = F.lit(True) if queries is None else F.coalesce(queries, F.lit(False))
    df = vectors.select(F.col(id_col).alias("own"), F.col(vector_col).alias("x"), ask.alias("ask")).where(F.col("own").isNotNull())
    single = df.schema["x"].dataType.elementType.simpleString() == "float"
    dtype, element = (np.float32, "float") if single else (np.float64, "double")
    df = df.select("own", F.col("x").cast(f"array<{element}>").alias("x"), "ask")
    df = df.where(F.col("x").isNotNull() & (F.size("x") > 0) & ~F.exists("x", lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == F.lit(float("inf")))))
    id_type = df.schema["own"].dataType.simpleString()
    names = None
    if id_type in ("tinyint", "smallint", "int", "bigint"):
        df = df.withColumn("id", F.col("own").cast("long")).drop("own")
    else:  # ids that aren't numbers are numbered in their order
        names = staged(row_numbers(df.select("own").distinct(), [F.col("own")], "id").withColumn("id", F.col("id").cast("long")), "ids")
        df = df.join(names, "own").drop("own")
    mean = F.aggregate("x", F.lit(0.0), lambda s, v: s + v.cast("double")) / F.size("x")
    df = staged(df.select("id", "x", "ask", F.size("x").alias("dim"), mean.alias("mean")), "vectors")
    parts = max(1, -(-df.count() // block))
    order = ["dim", "ask", "mean", "id"]
    ranged = df.repartitionByRange(parts, *order).sortWithinPartitions(*order)

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Blocks of one dimension, of queries or other rows, with box, ids, vectors and limits."""
        waiting: list[tuple[int, np.ndarray, bool]] = []

        def out() -> pa.RecordBatch:
            ids, x = np.array([w[0] for w in waiting], np.int64), np.array([w[1] for w in waiting], dtype)
            p = Prepared(ids, x)
            asks = waiting[0][2]
            limit = own_limits(p, k) if asks else np.full(len(ids), -np.inf)
            segments = levels_of(x.shape[1])
            s = statistics(p.x, segments[min(2, len(segments) - 1)])
            values = [[x.shape[1]], [asks], [ids.tobytes()], [x.tobytes()], [limit.tobytes()], [float(limit.max())], [s.min(0).astype(float).tolist()], [s.max(0).astype(float).tolist()]]
            types = [pa.int32(), pa.bool_(), pa.binary(), pa.binary(), pa.binary(), pa.float64(), pa.list_(pa.float64()), pa.list_(pa.float64())]
            return pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(values, types, strict=True)], names=["dim", "ask", "ids", "body", "limits", "reach", "lo", "hi"])

        for b in batches:
            for i, x, asks in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if waiting and (len(waiting[0][1]) != len(x) or waiting[0][2] != asks or len(waiting) >= 2 * block):
                    yield out()
                    waiting.clear()
                waiting.append((i, x, asks))
        if waiting:
            yield out()

    blocks = map_batches(ranged.select("id", "x", "ask"), packed, "dim int, ask boolean, ids binary, body binary, limits binary, reach double, lo array<double>, hi array<double>")
    blocks = staged(blocks.withColumn("no", F.monotonically_increasing_id()), "blocks")
    count = blocks.count()
    tasks = int(spark.conf.get("spark.sql.shuffle.partitions"))
    groups = max(1, min(count, max(int(np.ceil(np.sqrt(2 * tasks))), -(-count // group_blocks))))
    placed = staged(row_numbers(blocks.select("no", "dim", "ask", "reach", "lo", "hi"), [F.col("no")], "place", count).withColumn("g", F.struct("dim", "ask", F.floor((F.col("place") - 1) * groups / count).alias("g"))), "boxes")
    # boxes of groups: the least and greatest of each entry
    entry = placed.select("g", "reach", F.posexplode(F.arrays_zip("lo", "hi")).alias("e", "v")).groupBy("g", "e").agg(F.min("v.lo").alias("lo"), F.max("v.hi").alias("hi"), F.max("reach").alias("reach"))
    box = entry.groupBy("g").agg(F.max("reach").alias("reach"), F.array_sort(F.collect_list(F.struct("e", "lo", "hi"))).alias("v"))
    box = staged(box.select("g", "reach", F.col("v.lo").alias("lo"), F.col("v.hi").alias("hi")), "groups")
    left, right = box.select(*[F.col(c).alias(f"a_{c}") for c in box.columns]), box.select(*[F.col(c).alias(f"b_{c}") for c in box.columns])
    meet = (F.col("a_g.dim") == F.col("b_g.dim")) & (F.col("a_g") <= F.col("b_g")) & (F.expr(_APART) <= F.greatest("a_reach", "b_reach") + SLACK)
    cells = left.join(right, meet).select(F.col("a_g"), F.col("b_g"))
    cells = staged(cells.withColumn("cell", F.monotonically_increasing_id()), "cells")
    same = F.col("a_g") == F.col("b_g")
    to = cells.select(F.col("a_g").alias("g"), "cell", F.when(same, 2).otherwise(0).alias("side")).unionByName(cells.where(~same).select(F.col("b_g").alias("g"), "cell", F.lit(1).alias("side")))
    work = blocks.join(placed.select("no", "g").join(to, "g").select("no", "cell", "side"), "no").select("cell", "side", "no", "dim", "ids", "body", "limits", "lo", "hi")
    found = work.groupBy("cell").applyInArrow(_cell_kernel(k, dtype), "no long, at long, neighbour long, d double")
    rank = F.row_number().over(Window.partitionBy("no", "at").orderBy("d", "neighbour"))
    found = found.withColumn("rank", rank).where(F.col("rank") <= k)

    def identify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for no, raw in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                ids = np.frombuffer(raw, np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(ids), no)), pa.array(np.arange(len(ids))), pa.array(ids)], names=["no", "at", "id"])

    owner = map_batches(blocks.select("no", "ids"), identify, "no long, at long, id long")
    out = found.join(owner, ["no", "at"]).select("id", "rank", "neighbour", F.round(F.sqrt("d"), 6).alias("distance"))
    if names is None:
        return out.select(F.col("id").cast(id_type).alias(id_col), "rank", F.col("neighbour").cast(id_type).alias("neighbour"), "distance")
    out = out.join(names.select("id", F.col("own").alias(id_col)), "id").join(names.select(F.col("id").alias("neighbour"), F.col("own").alias("near")), "neighbour")
    return out.select(id_col, "rank", F.col("near").alias("neighbour"), "distance")
