"""Sampled Voronoi cells: seeds, tags by three ways, witness graph, volumes, shapes, queries and search by cells.

Seeds are the first S random ranks. A row's tag is its nearest seed (ties to the lower tag). Two seeds that are the
two nearest of some row share a cell border, so counting such rows gives true neighbours (some thin borders may go
unseen). Rows never travel to be tagged: seeds are broadcast after a check of their number.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellspace.functions.curves import curve_order
from cellspace.operators.grid import rank_hash
from cellspace.plans.shared import maybe_broadcast, staged

MAX_SEEDS = 100_000


@dataclass
class Seeds:
    tags: np.ndarray
    x: np.ndarray
    keys: np.ndarray

    def __post_init__(self):
        if len(self.tags) > MAX_SEEDS:
            raise ValueError("more seeds than a broadcast may hold: tag by kd leaves first")


def choose_seeds(df: DataFrame, cols: list[str], count: int, seed: int = 7, how: str = "random", order: str | None = None) -> Seeds:
    """``random``: the rows of least random hash. ``balanced``: the row nearest to the mean of each leaf (``df`` has a
    leaf). Tags 1..S follow the hash, or a space-filling curve if ``order`` names one."""
    if how == "balanced":
        mean = df.groupBy("leaf").agg(*[F.avg(c).alias(f"m{k}") for k, c in enumerate(cols)])
        d2 = sum(((F.col(c) - F.col(f"m{k}")) * (F.col(c) - F.col(f"m{k}")) for k, c in enumerate(cols)), F.lit(0.0))
        best = df.join(mean, "leaf").groupBy("leaf").agg(F.min(F.struct(d2.alias("d2"), "key", *cols)).alias("m"))
        got = best.select("m.key", *[f"m.{c}" for c in cols]).toArrow()
    else:
        got = df.select("key", *cols, rank_hash("key", seed).alias("h")).orderBy("h", "key").limit(count).toArrow()
    x = np.stack([got[c].to_numpy() for c in cols], 1)
    keys = got["key"].to_numpy()
    if order:
        at = np.lexsort((keys, curve_order(x, order)))
        x, keys = x[at], keys[at]
    return Seeds(np.arange(1, len(x) + 1), x, keys)


def two_nearest(x: np.ndarray, seeds: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(nearest, second, squared distance of the nearest) by position; exact sums of squares, ties to the lower."""
    d = np.zeros((len(x), len(seeds)))
    for k in range(x.shape[1]):
        gap = x[:, k, None] - seeds[None, :, k]
        d += gap * gap
    rows = np.arange(len(x))
    a = d.argmin(1)
    best = d[rows, a].copy()
    d[rows, a] = np.inf
    return a, (d.argmin(1) if len(seeds) > 1 else a), best


def greedy_graph(x: np.ndarray, edges: np.ndarray) -> list[np.ndarray]:
    near: list[list[int]] = [[] for _ in range(len(x))]
    for a, b in edges:
        near[a].append(b)
        near[b].append(a)
    return [np.array(sorted(n), int) for n in near]


def walk(points: np.ndarray, seeds: np.ndarray, near: list[np.ndarray], starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(seed where the walk ends, steps): all points hop at once to their nearest neighbour while that is nearer."""
    width = max([1, *map(len, near)])
    table = np.array([np.concatenate([n, np.full(width - len(n), k)]) for k, n in enumerate(near)], int)
    at, steps = starts.copy(), np.zeros(len(points), int)
    d = ((seeds[at] - points) ** 2).sum(1)
    live = np.arange(len(points))
    while len(live):
        options = table[at[live]]
        dn = ((seeds[options] - points[live, None]) ** 2).sum(2)
        j = dn.argmin(1)
        best = dn[np.arange(len(live)), j]
        go = best < d[live]
        live, options, j, best = live[go], options[go], j[go], best[go]
        at[live], d[live] = options[np.arange(len(live)), j], best
        steps[live] += 1
    return at, steps


def seed_tree(seeds: np.ndarray, leaf: int = 8) -> list:
    """Nested (axis, cut, left, right) or arrays of positions."""

    def build(ids: np.ndarray, depth: int):
        if len(ids) <= leaf:
            return ids
        axis = int((seeds[ids].max(0) - seeds[ids].min(0)).argmax())
        order = ids[np.argsort(seeds[ids, axis], kind="stable")]
        m = len(order) // 2
        return (axis, float(seeds[order[m], axis]), build(order[:m], depth + 1), build(order[m:], depth + 1))

    return build(np.arange(len(seeds)), 0)


def tree_nearest(tree, seeds: np.ndarray, points: np.ndarray) -> np.ndarray:
    """Nearest seed of each point, ties to the lower: all points go down together, split at each cut; those whose best
    is farther than the cut visit the other side as well."""
    best, at = np.full(len(points), np.inf), np.full(len(points), len(seeds))

    def visit(node, own: np.ndarray) -> None:
        if not len(own):
            return
        if isinstance(node, np.ndarray):
            ids = np.sort(node)
            d = np.zeros((len(own), len(ids)))
            for k in range(points.shape[1]):
                gap = points[own, k, None] - seeds[None, ids, k]
                d += gap * gap
            j = d.argmin(1)
            near, dist = ids[j], d[np.arange(len(own)), j]
            go = (dist < best[own]) | ((dist == best[own]) & (near < at[own]))
            best[own[go]], at[own[go]] = dist[go], near[go]
            return
        axis, cut, left, right = node
        low = points[own, axis] < cut
        visit(left, own[low])
        visit(right, own[~low])
        cross = (points[own, axis] - cut) ** 2 <= best[own]
        visit(right, own[low & cross])
        visit(left, own[~low & cross])

    visit(tree, np.arange(len(points)))
    return at


def tag_cells(df: DataFrame, cols: list[str], seeds: Seeds, how: str = "matrix", edges: np.ndarray | None = None, keep: list[str] | None = None) -> DataFrame:
    """``keep`` columns (key by default), cell_tag, second_tag, d2 and steps.

    ``matrix`` compares with all seeds, ``tree`` descends a tree over seeds, ``walk`` follows the neighbour graph from
    seed 0 and, as a partial graph may trap it, starts again from the best of a coarse sample of seeds and keeps the
    nearer end; steps are counted. Only ``matrix`` gives the second nearest.
    """
    keep = ["key"] if keep is None else keep
    sent = df.sparkSession.sparkContext.broadcast((seeds.tags, seeds.x))
    near = greedy_graph(seeds.x, edges) if how == "walk" else None
    schema = df.select(*keep).schema

    def kernel(batches):
        tags, sx = sent.value
        tree = seed_tree(sx) if how == "tree" else None
        coarse = np.arange(0, len(sx), max(1, int(np.sqrt(len(sx)))))
        step = max(1, 4_000_000 // max(1, len(sx)))
        for b in batches:
            x = np.stack([np.asarray(b.column(len(keep) + k)) for k in range(len(cols))], 1)
            a, second, d2, hops = np.zeros(len(x), int), np.full(len(x), -1), np.zeros(len(x)), np.zeros(len(x), int)
            if how == "matrix":
                for at in range(0, len(x), step):
                    s = slice(at, at + step)
                    a[s], second[s], d2[s] = two_nearest(x[s], sx)
            elif how == "tree":
                a = tree_nearest(tree, sx, x)
            else:
                a, hops = walk(x, sx, near, np.zeros(len(x), int))
                c = np.zeros(len(x), int)
                for at in range(0, len(x), step):
                    c[at : at + step] = coarse[two_nearest(x[at : at + step], sx[coarse])[0]]
                again, more = walk(x, sx, near, c)
                better = ((sx[again] - x) ** 2).sum(1) < ((sx[a] - x) ** 2).sum(1)
                a, hops = np.where(better, again, a), hops + np.where(better, more, 0)
            if how != "matrix":
                d2 = ((sx[a] - x) ** 2).sum(1)
            two = np.where(second >= 0, tags[np.maximum(second, 0)], 0)
            yield pa.RecordBatch.from_arrays([*b.columns[: len(keep)], pa.array(tags[a]), pa.array(two), pa.array(d2), pa.array(hops)], names=[*keep, "cell_tag", "second_tag", "d2", "steps"])

    return df.select(*keep, *cols).mapInArrow(kernel, ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in schema) + ", cell_tag long, second_tag long, d2 double, steps long")


def witness_graph(tagged: DataFrame) -> DataFrame:
    """(src, dst, witnesses) with src < dst, from rows with their two nearest tags."""
    some = tagged.where((F.col("second_tag") > 0) & (F.col("second_tag") != F.col("cell_tag")))
    return some.groupBy(F.least("cell_tag", "second_tag").alias("src"), F.greatest("cell_tag", "second_tag").alias("dst")).agg(F.count("*").alias("witnesses"))


def seed_graph(spark: SparkSession, seeds: Seeds, cols: list[str]) -> DataFrame:
    """Neighbours among many seeds without a pass over the rows: (src, dst) where the middle of two near seeds has the
    two as its nearest, which makes them true neighbours. Candidates are the 12 nearest of each seed."""
    from cellspace.operators.kdtree import build_kdtree
    from cellspace.operators.neighbours import knn_join

    s = spark.createDataFrame(pa.table([pa.array(seeds.tags), *(pa.array(np.ascontiguousarray(seeds.x[:, k])) for k in range(len(cols)))], names=["key", *cols]))
    index, tree = build_kdtree(s, cols)
    near = knn_join(s, index, tree, cols, 13, carry=cols).where("query_key < key")
    own = s.select(F.col("key").alias("query_key"), *[F.col(c).alias(f"o{k}") for k, c in enumerate(cols)])
    middle = near.join(own, "query_key").select(F.struct("query_key", "key").alias("pair"), *[((F.col(c) + F.col(f"o{k}")) / 2).alias(c) for k, c in enumerate(cols)])
    middle = staged(middle.select(F.concat_ws("|", "pair.query_key", "pair.key").alias("key"), *cols), "middles")
    two = knn_join(middle, index, tree, cols, 2).groupBy("query_key").agg(F.sort_array(F.collect_list("key")).alias("k"))
    ends = F.split("query_key", r"\|")
    return two.where((F.col("k")[0] == ends[0].cast("long")) & (F.col("k")[1] == ends[1].cast("long"))).select(F.col("k")[0].alias("src"), F.col("k")[1].alias("dst"))


def lattice(spark: SparkSession, lo, hi, per_axis: int) -> DataFrame:
    """Centres of a regular lattice of ``per_axis ** d`` voxels: key, x0.."""
    d = len(lo)
    out = spark.range(per_axis**d).withColumnRenamed("id", "key")
    for k, (a, b) in enumerate(zip(lo, hi, strict=True)):
        digit = F.floor(F.col("key") / per_axis ** (d - 1 - k)) % per_axis
        out = out.withColumn(f"x{k}", F.lit(float(a)) + (digit + 0.5) * ((float(b) - float(a)) / per_axis))
    return out


def cell_volume(spark: SparkSession, seeds: Seeds, lo, hi, per_axis: int, how: str = "lattice") -> DataFrame:
    """(cell_tag, probes, volume) by counting probe points; ``random`` scatters them (for higher dimensions)."""
    cols = [f"x{k}" for k in range(len(lo))]
    probes = lattice(spark, lo, hi, per_axis)
    n = per_axis ** len(lo)
    if how == "random":
        probes = spark.range(n).withColumnRenamed("id", "key")
        for k, (a, b) in enumerate(zip(lo, hi, strict=True)):
            u = F.pmod(F.xxhash64("key", F.lit(k)), F.lit(1 << 40)) / float(1 << 40)
            probes = probes.withColumn(f"x{k}", F.lit(float(a)) + u * (float(b) - float(a)))
    voxel = float(np.prod(np.array(hi, float) - np.array(lo, float)) / n)
    counts = tag_cells(probes, cols, seeds).groupBy("cell_tag").agg(F.count("*").alias("probes"))
    every = spark.createDataFrame([(int(t),) for t in seeds.tags], "cell_tag long")
    return every.join(counts, "cell_tag", "left").select("cell_tag", F.coalesce("probes", F.lit(0).cast("long")).alias("probes"), (F.coalesce("probes", F.lit(0)) * voxel).alias("volume"))


def cell_density(volumes: DataFrame, counts: DataFrame, kind: str = "inv_volume") -> DataFrame:
    """(cell_tag, volume, n, density): 1 / volume, or rows / volume. A cell without probes has the density of half a
    probe's volume."""
    least = volumes.where("volume > 0").agg(F.min("volume")).first()[0] or 1.0
    v = F.greatest(F.col("volume"), F.lit(least / 2))
    out = volumes.join(counts, "cell_tag", "left").withColumn("n", F.coalesce("n", F.lit(0).cast("long")))
    return out.select("cell_tag", "volume", "n", (F.lit(1.0) / v if kind == "inv_volume" else F.col("n") / v).alias("density"))


def clip_polygon(poly: np.ndarray, normal: np.ndarray, offset: float) -> np.ndarray:
    """The part of a convex polygon with normal . x <= offset."""
    out = []
    for a, b in zip(poly, np.roll(poly, -1, axis=0), strict=True):
        da, db = normal @ a - offset, normal @ b - offset
        if da <= 0:
            out.append(a)
        if (da < 0 < db) or (db < 0 < da):
            out.append(a + (b - a) * (da / (da - db)))
    return np.array(out).reshape(-1, 2)


def cell_polygons(seeds: np.ndarray, lo, hi) -> list[np.ndarray]:
    """Exact cells in two dimensions, by clipping the box with all bisectors."""
    frame = np.array([[lo[0], lo[1]], [hi[0], lo[1]], [hi[0], hi[1]], [lo[0], hi[1]]], float)
    out = []
    for i, s in enumerate(seeds):
        poly = frame
        for j in np.argsort(((seeds - s) ** 2).sum(1)):
            if j != i and len(poly):
                n = seeds[j] - s
                poly = clip_polygon(poly, n, float(n @ (seeds[j] + s) / 2))
        out.append(poly)
    return out


def polygon_area(p: np.ndarray) -> float:
    if len(p) < 3:
        return 0.0
    q = np.roll(p, -1, axis=0)
    return float(abs((p[:, 0] * q[:, 1] - q[:, 0] * p[:, 1]).sum()) / 2)


def delaunay_2d(seeds: np.ndarray) -> set[tuple[int, int]]:
    """Edges of pairs of seeds whose exact cells share a border (two dimensions, small sets)."""
    lo, hi = seeds.min(0) - 10 * np.ptp(seeds, 0) - 1, seeds.max(0) + 10 * np.ptp(seeds, 0) + 1
    edges = set()
    for i, poly in enumerate(cell_polygons(seeds, lo, hi)):
        for a, b in zip(poly, np.roll(poly, -1, axis=0), strict=True):
            m = (a + b) / 2
            d = ((seeds - m) ** 2).sum(1)
            j = np.argsort(d, kind="stable")[:2]
            if i in j and abs(d[j[0]] - d[j[1]]) < 1e-6 * (1 + d[j[0]]):
                edges.add((int(min(j)), int(max(j))))
    return edges


def cell_boxes(tagged_rows: DataFrame, cols: list[str]) -> DataFrame:
    """(cell_tag, n, lo.., hi..) boxes of the members of each cell."""
    aggs = [f(c).alias(f"{t}{k}") for k, c in enumerate(cols) for t, f in (("lo", F.min), ("hi", F.max))]
    return tagged_rows.groupBy("cell_tag").agg(F.count("*").alias("n"), *aggs)


def cell_balls(tagged_rows: DataFrame, cols: list[str], seeds: Seeds) -> DataFrame:
    """(cell_tag, n, radius, s..): the seed of each cell and the distance of its farthest member."""
    spark = tagged_rows.sparkSession
    s = spark.createDataFrame([(int(t), *map(float, x)) for t, x in zip(seeds.tags, seeds.x, strict=True)], "cell_tag long, " + ", ".join(f"s{k} double" for k in range(len(cols))))
    far = tagged_rows.groupBy("cell_tag").agg(F.count("*").alias("n"), F.sqrt(F.max("d2")).alias("radius"))
    return far.join(maybe_broadcast(s, len(seeds.tags)), "cell_tag")


def query_polyhedron_cells(tagged_rows: DataFrame, boxes: DataFrame, shape, cols: list[str], bound: str = "box") -> DataFrame:
    """Rows of the shape by cells, inside, outside or tested by ``bound``: the ``box`` of a cell's members (``boxes`` from
    ``cell_boxes``), or the ``ball`` around its seed (``boxes`` from ``cell_balls``)."""
    got = boxes.toArrow()
    d = len(cols)
    if bound == "box":
        lo, hi = np.stack([got[f"lo{k}"].to_numpy() for k in range(d)], 1), np.stack([got[f"hi{k}"].to_numpy() for k in range(d)], 1)
        kind = shape.classify(lo, hi)
    else:
        x, r = np.stack([got[f"s{k}"].to_numpy() for k in range(d)], 1), got["radius"].to_numpy() * (1 + 1e-12)
        inside, outside = np.ones(len(x), bool), np.zeros(len(x), bool)
        for f in shape.faces:
            at, reach = x @ np.array(f.w), r * np.linalg.norm(f.w)
            inside, outside = inside & (at + reach < f.b), outside | (at - reach > f.b)
        kind = np.where(outside, 0, np.where(inside, 2, 1))
    tags = got["cell_tag"].to_numpy()
    table = tagged_rows.sparkSession.createDataFrame([(int(t), bool(k == 2)) for t, k in zip(tags, kind, strict=True) if k], "cell_tag long, sure boolean")
    return tagged_rows.join(maybe_broadcast(table, len(tags)), "cell_tag").where(F.col("sure") | shape.column(cols)).drop("sure")


def delaunay_exact(seeds: np.ndarray) -> tuple[set[tuple[int, int]], np.ndarray]:
    """(edges, simplices) of the Delaunay tessellation in two or three dimensions, by insertion: simplices whose
    circumsphere holds the new seed go, and the border of the hole is joined to it. Small sets."""
    n, d = seeds.shape
    span = np.ptp(seeds, 0).max() or 1.0
    mid = seeds.mean(0)
    frame = np.concatenate([np.full((1, d), -1.0), np.eye(d) * d * 2 - 1]) * span * 1e3 + mid
    x = np.concatenate([seeds, frame])

    def sphere(s: tuple[int, ...]) -> tuple[np.ndarray, float]:
        p = x[list(s)]
        try:
            c = np.linalg.solve(2 * (p[1:] - p[0]), ((p[1:] - mid) ** 2).sum(1) - ((p[0] - mid) ** 2).sum()) + mid
        except np.linalg.LinAlgError:
            return mid, np.inf
        return c, float(((p[0] - c) ** 2).sum())

    first = tuple(range(n, n + d + 1))
    held = {first: sphere(first)}
    for i in range(n):
        gone = [s for s, (c, r) in held.items() if ((x[i] - c) ** 2).sum() < r * (1 + 1e-12)]
        faces: dict[tuple[int, ...], int] = {}
        for s in gone:
            del held[s]
            for k in range(d + 1):
                f = s[:k] + s[k + 1 :]
                faces[f] = faces.get(f, 0) + 1
        for f, times in faces.items():
            if times == 1:
                s = tuple(sorted((*f, i)))
                held[s] = sphere(s)
    real = np.array([s for s in held if s[-1] < n], int).reshape(-1, d + 1)
    edges = {(int(s[a]), int(s[b])) for s in real for a in range(d + 1) for b in range(a + 1, d + 1)}
    return edges, real


def knn_voronoi(points: np.ndarray, tagged_rows: DataFrame, seeds: Seeds, cols: list[str], k: int) -> DataFrame:
    """(query, rank, key, d2) of a few query points: cells in order of the distance to the bisector with the own cell,
    those beyond the k-th distance of the own cell's rows are left out."""
    spark = tagged_rows.sparkSession
    own = two_nearest(points, seeds.x)[0]
    q = spark.createDataFrame([(i, int(seeds.tags[o]), *map(float, p)) for i, (o, p) in enumerate(zip(own, points, strict=True))], "query int, cell_tag long, " + ", ".join(f"q{j} double" for j in range(len(cols))))
    qn = [f"q{j}" for j in range(len(cols))]
    from cellspace.operators.neighbours import squared_distance

    first = tagged_rows.join(F.broadcast(q), "cell_tag").withColumn("d2", squared_distance(cols, qn))
    got = first.groupBy("query").agg(F.sort_array(F.collect_list("d2")).alias("d")).select("query", F.when(F.size("d") >= k, F.col("d")[k - 1]).alias("m")).collect()
    reach = {r["query"]: np.inf if r["m"] is None else r["m"] for r in got}
    wanted = []
    for i, p in enumerate(points):
        s0 = seeds.x[own[i]]
        gap = seeds.x - s0
        norm = np.sqrt((gap**2).sum(1))
        norm[own[i]] = 1
        bisector = ((seeds.x + s0) / 2 * gap).sum(1) / norm - (p * gap).sum(1) / norm
        bisector[own[i]] = 0
        near = np.maximum(bisector, 0) ** 2 <= reach.get(i, np.inf) * (1 + 1e-9)
        wanted += [(i, int(t), *map(float, p)) for t in seeds.tags[near]]
    from pyspark.sql.window import Window

    q = spark.createDataFrame(wanted, q.schema)
    all_rows = tagged_rows.join(F.broadcast(q), "cell_tag").withColumn("d2", squared_distance(cols, qn))
    rank = F.row_number().over(Window.partitionBy("query").orderBy("d2", "key"))
    return all_rows.withColumn("rank", rank).where(F.col("rank") <= k).select("query", "rank", "key", "d2")


def tagged(df: DataFrame, cols: list[str], seeds: Seeds, extra: list[str] | None = None) -> DataFrame:
    """Key, coordinates and tags in the shared folder, laid out by tag."""
    rows = tag_cells(df, cols, seeds, keep=["key", *cols, *(extra or [])])
    return staged(rows.repartitionByRange("cell_tag").sortWithinPartitions("cell_tag", "key"), "cells")


def nested_graphs(df: DataFrame, cols: list[str], sizes: list[int]) -> dict[int, DataFrame]:
    """Witness graphs over growing prefixes of one random rank: (src, dst, witnesses) by number of seeds."""
    return {s: witness_graph(tag_cells(df, cols, choose_seeds(df, cols, s))) for s in sizes}


def edge_growth(counts: dict[int, int], target: int, row_bytes: int = 16) -> dict:
    """Edges of ``target`` seeds by a power law through the measured sizes, and their bytes."""
    s, e = np.log(list(counts)), np.log([max(1, v) for v in counts.values()])
    slope, base = np.polyfit(s, e, 1) if len(s) > 1 else (1.0, float(e[0] - s[0]))
    edges = float(np.exp(base + slope * np.log(target)))
    return {"slope": float(slope), "edges": edges, "bytes": edges * row_bytes}
