"""Polyhedron queries over a kd index, their baselines, batches and the choice between index and scan."""

from __future__ import annotations

from operator import or_

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cellspace.functions.shapes import HalfSpace, Polyhedron, Union, direction_set, hull_polyhedron_2d, joined
from cellspace.operators.kdtree import KdTree
from cellspace.plans.shared import maybe_broadcast

#: Intervals of a condition on leaves at most: each is a comparison a row, and more outgrow the compiled code.
MAX_RANGES = 32


def in_ranges(column: str, ranges: list[tuple[int, int]]) -> Column:
    return joined([F.col(column) == a if a == b else F.col(column).between(a, b) for a, b in ranges], or_, False)


def coalesced(ranges: list[tuple[int, int]], limit: int = MAX_RANGES) -> list[tuple[int, int]]:
    """At most ``limit`` intervals that cover the given ones: the narrowest gaps are closed first."""
    if len(ranges) <= limit:
        return ranges
    gaps = np.array([b[0] - a[1] for a, b in zip(ranges, ranges[1:], strict=False)])
    keep = np.sort(np.argsort(-gaps, kind="stable")[: limit - 1])
    out, start = [], ranges[0][0]
    for k in keep:
        out.append((start, ranges[k][1]))
        start = ranges[k + 1][0]
    return [*out, (start, ranges[-1][1])]


def scan_polyhedron(df: DataFrame, shape, cols: list[str], residual: Column | None = None) -> DataFrame:
    """The plain predicate: reads everything."""
    out = df.where(shape.column(cols))
    return out if residual is None else out.where(residual)


def query_polyhedron(index: DataFrame, tree: KdTree, shape, cols: list[str], residual: Column | None = None) -> DataFrame:
    """Exactly the rows of the scan, from the leaves inside (untested) and those on the surface (tested).

    Leaf conditions are ranges on the clustering column, so a clustered layout prunes files and row groups. Surface
    leaves beyond MAX_RANGES intervals are widened, which costs tests but never rows, as all but inside leaves are
    tested.
    """
    inside, partial, _ = tree.cover(shape)
    if not inside and not partial:
        return index.where(F.lit(False))
    touched = coalesced(sorted([*inside, *partial]))
    sure = in_ranges("leaf", inside) if len(inside) <= MAX_RANGES else F.lit(False)
    out = index.where(in_ranges("leaf", touched)).where(sure | shape.column(cols))
    return out if residual is None else out.where(residual)


def query_dnf(index: DataFrame, tree: KdTree, parts: list, residuals: list[Column | None], cols: list[str]) -> DataFrame:
    """Rows of any of several polyhedra, each with a residual condition of its own, from one scan of the leaves that any
    of them touches. A row is tested once, so none comes twice."""
    touched, met = [], F.lit(False)
    for p, r in zip(parts, residuals, strict=True):
        inside, partial, _ = tree.cover(p)
        touched += [*inside, *partial]
        met = met | (p.column(cols) if r is None else p.column(cols) & r)
    if not touched:
        return index.where(F.lit(False))
    runs: list[tuple[int, int]] = []
    for a, b in sorted(touched):
        if runs and a <= runs[-1][1] + 1:
            runs[-1] = (runs[-1][0], max(runs[-1][1], b))
        else:
            runs.append((a, b))
    return index.where(in_ranges("leaf", coalesced(runs))).where(F.coalesce(met, F.lit(False)))


def poly_cost(tree: KdTree, shape) -> dict:
    """Leaves inside, partial and outside, rows examined by the index and rows of the table."""
    _, _, t = tree.cover(shape)
    return {**t, "rows_read": t["rows_inside"] + t["rows_partial"], "rows": int(tree.counts[1])}


def choose_plan(tree: KdTree, shape, threshold: float = 0.25) -> tuple[str, float, float]:
    """('index' or 'scan', estimated share returned, share of rows read). Half of the surface rows count as returned."""
    c = poly_cost(tree, shape)
    n = max(c["rows"], 1)
    returned, read = (c["rows_inside"] + c["rows_partial"] / 2) / n, c["rows_read"] / n
    return ("index" if returned < threshold and read < 0.9 else "scan"), returned, read


def planned_query(index: DataFrame, tree: KdTree, shape, cols: list[str], threshold: float = 0.25) -> DataFrame:
    plan, _, _ = choose_plan(tree, shape, threshold)
    return query_polyhedron(index, tree, shape, cols) if plan == "index" else scan_polyhedron(index, shape, cols)


def query_many(index: DataFrame, tree: KdTree, shapes: dict[int, object], cols: list[str], key: str = "key") -> DataFrame:
    """(query_id, key) of many shapes in one pass: leaf covers become a table that is joined by leaf."""
    covers = []
    for q, s in shapes.items():
        inside, partial, _ = tree.cover(s)
        covers += [(q, j, True) for a, b in inside for j in range(a, b + 1)] + [(q, j, False) for a, b in partial for j in range(a, b + 1)]
    spark = index.sparkSession
    table = spark.createDataFrame(covers, "query_id int, leaf long, sure boolean")
    met = F.lit(False)
    for q, s in shapes.items():
        met = met | ((F.col("query_id") == q) & s.column(cols))
    return index.join(maybe_broadcast(table, len(covers)), "leaf").where(F.col("sure") | met).select("query_id", key)


def uniform_grid_query(df: DataFrame, cols: list[str], shape, bins: int, lo, hi) -> tuple[DataFrame, DataFrame]:
    """Equal bins: (rows found by cells that meet the shape's cells, occupied cells with counts)."""
    cell = F.lit(0).cast("long")
    for c, a, b in zip(cols, lo, hi, strict=True):
        cell = cell * bins + F.least(F.greatest(F.floor((F.col(c) - float(a)) / max(float(b) - float(a), 1e-300) * bins), F.lit(0)), F.lit(bins - 1))
    celled = df.withColumn("cell", cell)
    occupied = celled.groupBy("cell").agg(F.count("*").alias("n"))
    d = len(cols)
    idx = np.stack(np.meshgrid(*[np.arange(bins)] * d, indexing="ij"), -1).reshape(-1, d)
    lo, width = np.array(lo, float), (np.array(hi, float) - np.array(lo, float)) / bins
    kinds = shape.classify(lo + idx * width, lo + (idx + 1) * width)
    edge = ((idx == 0) | (idx == bins - 1)).any(1)  # clamped rows may lie beyond the border
    table = df.sparkSession.createDataFrame([(int(k), bool(kinds[k] == 2 and not edge[k])) for k in np.flatnonzero((kinds > 0) | edge)], "cell long, sure boolean")
    return celled.join(F.broadcast(table) if bins**d <= 1_000_000 else table, "cell").where(F.col("sure") | shape.column(cols)), occupied


def hull_query(train: DataFrame, cols: list[str], kind: str = "directions") -> Polyhedron:
    """A polyhedron around a training set: its greatest extent in fixed directions, or the exact hull in two dimensions.

    ``directions`` is one aggregation; ``exact2d`` first keeps the extreme rows of 64 directions to bound what is
    collected only if the set is large, else collects it.
    """
    if kind == "exact2d":
        got = train.select(*cols).distinct().toArrow()
        return hull_polyhedron_2d(np.stack([got[c].to_numpy() for c in cols], 1))
    rays = direction_set(len(cols))
    aggs = []
    for k, r in enumerate(rays):
        dot = None
        for w, c in zip(r, cols, strict=True):
            if w:
                term = F.col(c) * w
                dot = term if dot is None else dot + term
        aggs.append(F.max(dot).alias(f"d{k}"))
    row = train.agg(*aggs).first()
    return Polyhedron(tuple(HalfSpace(r, float(row[f"d{k}"])) for k, r in enumerate(rays) if row[f"d{k}"] is not None))


def linear_separator(train: DataFrame, cols: list[str], label: str) -> HalfSpace:
    """The half-space of class 1 by linear discriminant: pooled covariance from one aggregation by class."""
    d = len(cols)
    aggs = [F.count("*").alias("n")] + [F.avg(c).alias(f"m{i}") for i, c in enumerate(cols)] + [F.covar_pop(a, b).alias(f"c{i}_{j}") for i, a in enumerate(cols) for j, b in enumerate(cols) if i <= j]
    rows = {r[label]: r for r in train.groupBy(label).agg(*aggs).collect()}
    mean = {k: np.array([rows[k][f"m{i}"] for i in range(d)]) for k in (0, 1)}
    cov = sum(rows[k]["n"] * np.array([[rows[k][f"c{min(i, j)}_{max(i, j)}"] for j in range(d)] for i in range(d)]) for k in (0, 1))
    n = rows[0]["n"] + rows[1]["n"]
    w = np.linalg.solve(cov / n + 1e-9 * np.eye(d), mean[1] - mean[0])
    cut = w @ (mean[0] + mean[1]) / 2 - np.log(rows[1]["n"] / rows[0]["n"])
    return HalfSpace(tuple(map(float, -w)), float(-cut))


def boxes_frame(spark, tree: KdTree) -> DataFrame:
    """Leaf boxes as a table: leaf, n, lo.., hi.."""
    lo, hi = tree.leaf_boxes()
    some = np.flatnonzero(tree.counts[tree.leaves :])
    d = tree.dim
    table = pa.table([pa.array(some), pa.array(tree.counts[tree.leaves :][some]), *(pa.array(lo[some, k].copy()) for k in range(d)), *(pa.array(hi[some, k].copy()) for k in range(d))], names=["leaf", "n", *(f"lo{k}" for k in range(d)), *(f"hi{k}" for k in range(d))])
    return spark.createDataFrame(table)


def classify_cells(boxes: DataFrame, shape: Polyhedron, d: int) -> DataFrame:
    """Adds ``kind`` (outside, partial, inside) to boxes with lo.. and hi.. columns, by column expressions."""
    inside, outside = F.lit(True), F.lit(False)
    for f in shape.faces:
        low = high = None
        for k, w in enumerate(f.w):
            if w:
                a, b = (F.col(f"lo{k}") * w, F.col(f"hi{k}") * w) if w > 0 else (F.col(f"hi{k}") * w, F.col(f"lo{k}") * w)
                low, high = (a, b) if low is None else (low + a, high + b)
        inside, outside = inside & (high <= f.b), outside | (low > f.b)
    return boxes.withColumn("kind", F.when(outside, "outside").when(inside, "inside").otherwise("partial"))


__all__ = ["Union", "query_polyhedron", "scan_polyhedron"]
