"""Exact nearest neighbours over a kd index, the boundary-point variant, batch joins and brute force.

The batch join takes two rounds for any number of queries: the home node gives an upper bound of the k-th distance,
then all leaves whose box is nearer than that are searched, found by descent. A leaf meets all its queries as one matrix
of distances, and only k rows a query leave it. Distances are sums of squares in coordinate order, ties go
to the lower key.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cellspace.operators.kdtree import KdTree
from cellspace.plans.shared import maybe_broadcast, staged


def squared_distance(a: list[str], b: list[str]) -> Column:
    out = None
    for x, y in zip(a, b, strict=True):
        term = (F.col(x) - F.col(y)) * (F.col(x) - F.col(y))
        out = term if out is None else out + term
    return out


def squared_distance_sql(a: str, b: str, d: int) -> str:
    return " + ".join(f"({a}x{k} - {b}x{k}) * ({a}x{k} - {b}x{k})" for k in range(d))


def _as_queries(queries: DataFrame, cols: list[str], key: str) -> DataFrame:
    return queries.select(F.col(key).alias("query_key"), *[F.col(c).alias(f"q{k}") for k, c in enumerate(cols)])


def _ranked(found: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("query_key").orderBy("d2", "key")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def knn_brute(queries: DataFrame, points: DataFrame, cols: list[str], k: int, count: int, key: str = "key") -> DataFrame:
    """(query_key, rank, key, d2): every pair is compared; the queries are the side that is copied."""
    q = _as_queries(queries, cols, key)
    pts = points.select("key", *cols)
    pairs = pts.crossJoin(maybe_broadcast(q, count)).withColumn("d2", squared_distance(cols, [f"q{j}" for j in range(len(cols))]))
    return _ranked(pairs.select("query_key", "key", "d2"), k).select("query_key", "rank", "key", "d2")


#: Bytes of an indexed table that every worker may hold for a map-only join.
HELD_BYTES = 64_000_000


def nearest_rows(d2: np.ndarray, keys: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(query, column) of the k least entries of each row of a distance matrix, ties by key."""
    if d2.shape[1] > k:
        kth = np.partition(d2, k - 1, axis=1)[:, k - 1]
        i, j = np.nonzero(d2 <= kth[:, None])
    else:
        i, j = np.nonzero(d2 < np.inf)
    return first_k(i, d2[i, j], keys[j], k, (i, j))


def first_k(query: np.ndarray, d2: np.ndarray, keys: np.ndarray, k: int, columns: tuple) -> tuple:
    """``columns`` of the k first of each query by distance and key. Rows beyond a query's k-th distance are left out of
    the sort."""
    count = np.bincount(query) if len(query) else np.zeros(0, np.int64)
    width = int(count.max(initial=0))
    if width > k and len(count) <= 1 << 16 and len(count) * width <= 8 * len(query):
        order = np.argsort(query.astype(np.uint16), kind="stable")
        table = np.full((len(count), width), np.inf)
        table[query[order], np.arange(len(query)) - np.repeat(np.cumsum(count) - count, count)] = d2[order]
        near = d2 <= np.partition(table, k - 1, axis=1)[query, k - 1]
        query, d2, keys, columns = query[near], d2[near], keys[near], tuple(c[near] for c in columns)
    order = np.lexsort((keys, d2, query))
    q = query[order]
    start = np.flatnonzero(np.diff(q, prepend=q[:1] - 1))
    rank = np.arange(len(q)) - np.repeat(start, np.diff(np.append(start, len(q))))
    order = order[rank < k]
    return tuple(c[order] for c in columns)


def distances(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Squared distances in the order of coordinates, as the SQL form has them."""
    out = np.zeros((len(x), len(y)))
    for k in range(x.shape[1]):
        gap = y[None, :, k] - x[:, None, k]
        out += gap * gap
    return out


#: From so many coordinates on, a matrix product picks the pairs whose distances are worth adding up.
PRODUCT_DIM = 16


def pairs_within(x: np.ndarray, y: np.ndarray, bound: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row of x, row of y, squared distance) of all pairs within the bound of x. The product only picks: its slack is far
    beyond its rounding, and distances are those of ``distances``."""
    xx, yy = (x * x).sum(1), (y * y).sum(1)
    slack = 1e-11 * (xx + yy.max(initial=0.0))
    i, j = np.nonzero(yy[None] - 2 * (x @ y.T) <= (bound - xx + slack)[:, None])
    d2 = np.zeros(len(i))
    for k in range(x.shape[1]):
        gap = y[j, k] - x[i, k]
        d2 += gap * gap
    keep = d2 <= bound[i]
    return i[keep], j[keep], d2[keep]


class HeldIndex:
    """An indexed table in memory, rows in leaf order."""

    def __init__(self, tree: KdTree, leaf: np.ndarray, keys: np.ndarray, x: np.ndarray):
        order = np.lexsort((keys, leaf))
        self.tree, self.order, self.keys, self.x = tree, order, keys[order], x[order]
        self.start = np.searchsorted(leaf[order], np.arange(tree.leaves + 1))

    def search(self, x: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(query, row, squared distance) of the k nearest rows, in order. The home node bounds the k-th distance; all
        other leaves within it follow, each against all its queries at once."""
        t = self.tree
        home = t.home(x, k)
        first, past = t.leaf_range(home)
        bound, found = np.full(len(x), np.inf), []

        def visit(own: np.ndarray, a: int, b: int, limit: bool) -> None:
            for at in range(0, len(own), max(1, 2_000_000 // max(1, b - a))):
                some = own[at : at + max(1, 2_000_000 // max(1, b - a))]
                if limit and x.shape[1] >= PRODUCT_DIM:
                    i, j, d = pairs_within(x[some], self.x[a:b], bound[some])
                    i, j, d = first_k(i, d, self.keys[a + j], k, (i, j, d))
                    found.append((some[i], a + j, d))
                    continue
                d2 = distances(x[some], self.x[a:b])
                if limit:
                    near = d2 <= bound[some, None]
                    if np.count_nonzero(near) <= 4 * k * len(some):  # few: they are ranked once, at the end
                        i, j = np.nonzero(near)
                        found.append((some[i], a + j, d2[i, j]))
                        continue
                    d2[~near] = np.inf
                i, j = nearest_rows(d2, self.keys[a:b], k)
                d = d2[i, j]
                keep = d < np.inf
                i, j, d = i[keep], j[keep], d[keep]
                found.append((some[i], a + j, d))
                if not limit:
                    full = np.bincount(i, minlength=len(some)) >= k
                    far = np.zeros(len(some))
                    np.maximum.at(far, i, d)
                    bound[some[full]] = far[full]

        def runs(groups: np.ndarray):
            order = np.argsort(groups, kind="stable")
            edges = np.flatnonzero(np.diff(groups[order], prepend=-1))
            yield from ((int(groups[p[0]]), p) for p in np.split(order, edges[1:]) if len(p))

        for node, own in runs(home):
            lo, hi = t.leaf_range(np.array([node]))
            visit(own, self.start[lo[0]], self.start[hi[0]], False)
        i, leaf = t.leaves_within(x, bound)
        other = (leaf < first[i]) | (leaf >= past[i])
        i, leaf = i[other], leaf[other]
        for j, at in runs(leaf):
            visit(i[at], self.start[j], self.start[j + 1], True)
        q, row, d = (np.concatenate(c) for c in zip(*found, strict=True)) if found else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
        return first_k(q, d, self.keys[row], k, (q, row, d))


def _ranks(query: np.ndarray) -> np.ndarray:
    start = np.flatnonzero(np.diff(query, prepend=query[:1] - 1))
    return np.arange(len(query)) - np.repeat(start, np.diff(np.append(start, len(query)))) + 1


def knn_join(queries: DataFrame, index: DataFrame, tree: KdTree, cols: list[str], k: int, key: str = "key", carry: list[str] | None = None) -> DataFrame:
    """(query_key, rank, key, d2, *carry): the k nearest indexed rows of each query; all rows if there are fewer than k.
    ``carry`` names further columns of the index.

    An index within HELD_BYTES is held by every worker: a pass over the queries that moves nothing. A larger one is
    met leaf by leaf: queries go to their home leaf, then to all other leaves within the bound found there.
    """
    carry = carry or []
    q = _as_queries(queries, cols, key)
    kinds = {f.name: f.dataType.simpleString() for f in index.schema}
    out = [f"query_key {q.schema['query_key'].dataType.simpleString()}", "rank int", f"key {kinds['key']}", "d2 double", *(f"`{c}` {kinds[c]}" for c in carry)]
    names = ["query_key", "rank", "key", "d2", *carry]
    d = len(cols)
    width = 8 * (d + 2) + sum({"string": 40}.get(kinds[c], 8) for c in carry)
    if int(tree.counts[1]) * width > HELD_BYTES:
        return _knn_by_leaf(q, index.select("leaf", "key", *cols), tree, cols, k, index.select("key", *carry) if carry else None)
    got = index.select("leaf", "key", *cols, *[F.col(c).alias(f"__carried{i}") for i, c in enumerate(carry)]).toArrow()
    sent = q.sparkSession.sparkContext.broadcast((tree, got.combine_chunks()))

    def kernel(batches):
        t, table = sent.value
        x = np.stack([table[c].to_numpy() for c in cols], 1) if table.num_rows else np.zeros((0, d))
        held = HeldIndex(t, table["leaf"].to_numpy(), table["key"].to_numpy(), x)
        extra = [table[f"__carried{i}"].combine_chunks().take(pa.array(held.order)) for i in range(len(carry))]
        for b in batches:
            if not b.num_rows or not table.num_rows:
                continue
            points = np.stack([np.asarray(b.column(1 + j)) for j in range(d)], 1)
            i, row, d2 = held.search(points, k)
            at = pa.array(row)
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(i)), pa.array(_ranks(i).astype(np.int32)), pa.array(held.keys[row]), pa.array(d2), *(c.take(at) for c in extra)], names=names)

    return q.mapInArrow(kernel, ", ".join(out))


def _leaf_lists(q: DataFrame, tree: KdTree, d: int, k: int, first: bool) -> DataFrame:
    """Rows (query_key, q.., bound, leaf): the leaves of the home node, or all leaves within ``bound`` but those."""
    sent = q.sparkSession.sparkContext.broadcast(tree)
    names = ["query_key", *[f"q{j}" for j in range(d)], "bound"]

    def kernel(batches):
        t = sent.value
        for b in batches:
            x = np.stack([np.asarray(b.column(1 + j)) for j in range(d)], 1)
            lo, hi = t.leaf_range(t.home(x, k))
            if first:
                i = np.repeat(np.arange(len(x)), hi - lo)
                leaf = np.concatenate([np.arange(a, e) for a, e in zip(lo, hi, strict=True)]) if len(x) else i
            else:
                i, leaf = t.leaves_within(x, np.asarray(b.column(1 + d)))
                other = (leaf < lo[i]) | (leaf >= hi[i])
                i, leaf = i[other], leaf[other]
            rows = pa.array(i)
            yield pa.RecordBatch.from_arrays([*(c.take(rows) for c in b.columns), pa.array(leaf.astype(np.int64))], names=[*names, "leaf"])

    kind = q.schema["query_key"].dataType.simpleString()
    return q.select(*names).mapInArrow(kernel, f"query_key {kind}, " + ", ".join(f"q{j} double" for j in range(d)) + ", bound double, leaf long")


def _met(lists: DataFrame, points: DataFrame, cols: list[str], k: int, query_rows: int = 50_000, tell: bool = False) -> DataFrame:
    """(query_key, key, d2): of each leaf that a query lists, the k nearest of its points within the query's bound; with
    ``tell`` also the leaf. A leaf with many queries is met in parts of about ``query_rows``."""
    d = len(cols)
    kind, own = lists.schema["query_key"].dataType.simpleString(), points.schema["key"].dataType.simpleString()

    def block(left: pa.Table, right: pa.Table) -> pa.Table:
        qx = np.stack([left[f"q{j}"].to_numpy() for j in range(d)], 1)
        px = np.stack([right[c].to_numpy() for c in cols], 1) if right.num_rows else np.zeros((0, d))
        keys, bound, parts = right["key"].to_numpy(), left["bound"].to_numpy(), []
        step = max(1, 2_000_000 // max(1, len(px)))
        for at in range(0, len(qx) if len(px) else 0, step):
            d2 = distances(qx[at : at + step], px)
            d2[d2 > bound[at : at + step, None]] = np.inf
            i, j = nearest_rows(d2, keys, k)
            keep = d2[i, j] < np.inf
            parts.append((i[keep] + at, j[keep], d2[i, j][keep]))
        i, j, dd = (np.concatenate(c) for c in zip(*parts, strict=True)) if parts else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
        at = pa.array(i)
        where = [left["leaf"].combine_chunks().take(at)] if tell else []
        return pa.table([left["query_key"].combine_chunks().take(at), right["key"].combine_chunks().take(pa.array(j)), pa.array(dd), *where], names=["query_key", "key", "d2", *["leaf"][: len(where)]])

    lists = staged(lists, "lists")
    parts = lists.groupBy("leaf").agg(F.ceil(F.count("*") / query_rows).cast("int").alias("parts"))
    salted = lists.join(parts, "leaf").withColumn("part", F.pmod(F.xxhash64("query_key"), F.col("parts"))).drop("parts")
    copies = points.join(parts, "leaf").withColumn("part", F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts").cast("long") - 1))).drop("parts")
    return salted.groupBy("leaf", "part").cogroup(copies.groupBy("leaf", "part")).applyInArrow(block, f"query_key {kind}, key {own}, d2 double" + (", leaf long" if tell else ""))


def _knn_by_leaf(q: DataFrame, points: DataFrame, tree: KdTree, cols: list[str], k: int, carried: DataFrame | None) -> DataFrame:
    """Two rounds of cogroups by leaf."""
    d = len(cols)
    q = staged(q, "queries")
    near = _met(_leaf_lists(q.withColumn("bound", F.lit(float("inf"))), tree, d, k, True), points, cols, k)
    first = staged(_ranked(near, k).select("query_key", "key", "d2"), "round1")
    bound = first.groupBy("query_key").agg(F.max("d2").alias("m"), F.count("*").alias("n"))
    bounded = q.join(bound, "query_key", "left").withColumn("bound", F.when(F.col("n") >= k, F.col("m")).otherwise(F.lit(float("inf"))))
    out = _ranked(first.unionByName(_met(_leaf_lists(bounded, tree, d, k, False), points, cols, k)), k).select("query_key", "rank", "key", "d2")
    return out if carried is None else out.join(carried, "key").select("query_key", "rank", "key", "d2", *[c for c in carried.columns if c != "key"])


def knn_point(index: DataFrame, tree: KdTree, point, cols: list[str], k: int, bound: str = "box", refine: bool = True) -> tuple[list[tuple[int, float]], list[dict]]:
    """((key, squared distance) of the k nearest, trace) of one point, growing leaf by leaf.

    ``bound='box'`` visits unread leaves by distance of their tight boxes and stops when the next is beyond the k-th
    distance: exact. ``bound='boundary_points'`` judges by corners of read leaves and the point's projections on their
    faces, as a cheaper reading of the region's border; it may stop too early in three dimensions or more.
    ``refine`` asks a new leaf only for the places that are not yet certain.
    """
    p = np.asarray(point, float)
    lo, hi = tree.leaf_boxes()
    if tree.region_lo is not None:  # the rule walks boxes that fill the space
        lo, hi = tree.region_lo[tree.leaves :], tree.region_hi[tree.leaves :]
    nodes = np.arange(tree.leaves, 2 * tree.leaves)
    box_d = tree.box_distance2(p[None], nodes)[0]
    best: list[tuple[float, int]] = []
    read: set[int] = set()
    trace = []
    # d2 of the home leaf is 0 for a point inside; a point outside all boxes starts at the nearest
    todo = [int(np.argmin(box_d))]
    while todo:
        leaf = todo.pop(0)
        read.add(leaf)
        kth = best[k - 1][0] if len(best) >= k else np.inf
        sure = sum(1 for dd, _ in best if dd < box_d[leaf])
        need = k - sure if refine else k
        d2 = F.lit(0.0)
        for c, v in zip(cols, p, strict=True):
            d2 = d2 + (F.col(c) - float(v)) * (F.col(c) - float(v))
        rows = index.where(F.col("leaf") == leaf).select("key", d2.alias("d2")).where(F.col("d2") <= float(kth)).orderBy("d2", "key").limit(need).collect()
        best = sorted([*best, *((r["d2"], r["key"]) for r in rows)])[:k]
        kth = best[k - 1][0] if len(best) >= k else np.inf
        trace.append({"step": len(trace) + 1, "leaf": leaf, "bound": float(box_d[leaf]), "sure": sure, "kth": float(kth)})
        unread = [j for j in range(tree.leaves) if j not in read and tree.counts[tree.leaves + j]]
        if bound == "box":
            near = [j for j in unread if box_d[j] <= kth]
            todo = [min(near, key=lambda j: (box_d[j], j))] if near else []
        else:
            todo = _frontier(p, lo, hi, sorted(read), unread, kth)
    return [(key, d) for d, key in best], trace


def _border(p: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """Corners of a box and the point's projections on its faces."""
    d = len(p)
    corners = np.stack(np.meshgrid(*[[lo[k], hi[k]] for k in range(d)], indexing="ij"), -1).reshape(-1, d)
    faces = np.repeat(np.clip(p, lo, hi)[None], 2 * d, 0)
    for k in range(d):
        faces[2 * k, k], faces[2 * k + 1, k] = lo[k], hi[k]
    return np.concatenate([corners, faces])


def _frontier(p: np.ndarray, lo: np.ndarray, hi: np.ndarray, read: list[int], unread: list[int], kth: float) -> list[int]:
    """The unread leaf that holds the nearest border point (corner or projection) of the read leaves within ``kth``."""
    pts = np.concatenate([_border(p, lo[r], hi[r]) for r in read])
    dist = ((pts - p) ** 2).sum(1)
    u = np.array(unread, int)
    for k in np.argsort(dist, kind="stable"):
        if dist[k] > kth or not len(u):
            return []
        touch = u[((lo[u] <= pts[k]) & (pts[k] <= hi[u])).all(1)]
        if len(touch):
            return [int(touch[0])]
    return []


def hold(index: DataFrame, tree: KdTree, cols: list[str]) -> HeldIndex:
    """An index in the driver's memory, within HELD_BYTES."""
    if int(tree.counts[1]) * 8 * (len(cols) + 2) > HELD_BYTES:
        raise ValueError("too large to hold: ask point by point")
    got = index.select("leaf", "key", *cols).toArrow()
    return HeldIndex(tree, got["leaf"].to_numpy(), got["key"].to_numpy(), np.stack([got[c].to_numpy() for c in cols], 1))


def bound_recall(held: HeldIndex, points: np.ndarray, k: int, bound: str) -> tuple[float, int, float]:
    """(share of the true k nearest found, points with a wrong answer, mean leaves read) of a stopping rule."""
    t = held.tree
    lo, hi = t.region_lo[t.leaves :], t.region_hi[t.leaves :]
    nodes = np.arange(t.leaves, 2 * t.leaves)
    right = wrong = leaves = 0
    for p in points:
        d2 = distances(p[None], held.x)[0]
        truth = set(np.lexsort((held.keys, d2))[:k].tolist())
        box_d = t.box_distance2(p[None], nodes)[0]
        todo, read, best = [int(np.argmin(box_d))], [], np.zeros(0, int)
        while todo:
            leaf = todo[0]
            read.append(leaf)
            best = np.concatenate([best, np.arange(held.start[leaf], held.start[leaf + 1])])
            best = best[np.lexsort((held.keys[best], d2[best]))[:k]]
            kth = d2[best[k - 1]] if len(best) >= k else np.inf
            unread = np.setdiff1d(np.flatnonzero(t.counts[nodes] > 0), read)
            if bound == "box":
                near = unread[box_d[unread] <= kth]
                todo = [int(near[np.lexsort((near, box_d[near]))[0]])] if len(near) else []
            else:
                todo = _frontier(p, lo, hi, read, unread.tolist(), kth)
        hit = len(truth & set(best.tolist()))
        right, wrong, leaves = right + hit, wrong + (hit < min(k, len(d2))), leaves + len(read)
    return right / (k * len(points)), wrong, leaves / len(points)


class Borders:
    """What the boundary-point rule asks of a leaf's region, made once a leaf: corners, touching leaves with rows, and
    which corner lies on which of them."""

    def __init__(self, tree: KdTree):
        self.tree, self.lo, self.hi = tree, tree.region_lo[tree.leaves :], tree.region_hi[tree.leaves :]
        self.some, self.made = tree.counts[tree.leaves :] > 0, {}

    def of(self, leaf: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        if leaf not in self.made:
            lo, hi = self.lo[leaf], self.hi[leaf]
            near = self.some & (self.lo <= hi).all(1) & (lo <= self.hi).all(1)
            near[leaf] = False
            around = np.flatnonzero(near)
            corners = np.stack(np.meshgrid(*[[lo[k], hi[k]] for k in range(len(lo))], indexing="ij"), -1).reshape(-1, len(lo))
            touch = ((self.lo[around][None] <= corners[:, None]) & (corners[:, None] <= self.hi[around][None])).all(2)
            self.made[leaf] = around, corners, touch
        return self.made[leaf]

    def reach(self, points: np.ndarray, leaf: int, least: np.ndarray) -> np.ndarray:
        """``least`` [points, touching leaves] lowered to the distance of the nearest border point of ``leaf`` on them."""
        around, corners, touch = self.of(leaf)
        d = points.shape[1]
        far = ((points[:, None] - corners[None]) ** 2).sum(2)
        for c, on in enumerate(touch):
            if on.any():
                least[:, on] = np.minimum(least[:, on], far[:, c, None])
        at = np.clip(points, self.lo[leaf], self.hi[leaf])
        gap = (at - points) ** 2
        met = [(self.lo[around, k] <= at[:, k, None]) & (at[:, k, None] <= self.hi[around, k]) for k in range(d)]
        for k in range(d):
            others = np.ones(least.shape, bool)
            for j in range(d):
                if j != k:
                    others &= met[j]
            rest = gap.sum(1) - gap[:, k]
            for v in (self.lo[leaf, k], self.hi[leaf, k]):
                on = others & ((self.lo[around, k] <= v) & (v <= self.hi[around, k]))[None]
                np.minimum(least, (rest + (v - points[:, k]) ** 2)[:, None], out=least, where=on)
        return least


def boundary_walk(borders: Borders, points: np.ndarray, near, k: int) -> np.ndarray:
    """[points, leaves]: the leaves that the boundary-point rule reads for each point, all points a step at a time.

    From the point's own leaf it goes on to the unread leaf that holds the nearest border point of the read ones, while
    that is within the k-th distance (ties to the lower leaf). ``near(leaf, own)`` gives the k least squared distances
    of ``points[own]`` to the rows of a leaf, infinity where there are fewer.
    """
    t = borders.tree
    read, least = np.zeros((len(points), t.leaves), bool), np.full((len(points), t.leaves), np.inf)
    best = np.full((len(points), k), np.inf)
    active, leaf = np.arange(len(points)), t.locate(points)
    while len(active):
        order = np.argsort(leaf, kind="stable")
        for part in np.split(order, np.flatnonzero(np.diff(leaf[order])) + 1):
            own, at = active[part], int(leaf[part[0]])
            read[own, at], least[own, at] = True, np.inf
            best[own] = np.partition(np.concatenate([best[own], near(at, own)], 1), k - 1, axis=1)[:, :k]
            around = borders.of(at)[0]
            if len(around):
                cells = np.ix_(own, around)
                reached = borders.reach(points[own], at, least[cells])
                reached[read[cells]] = np.inf
                least[cells] = reached
        leaf = least[active].argmin(1)
        far = least[active, leaf]
        go = (far < np.inf) & (far <= best[active].max(1))
        active, leaf = active[go], leaf[go]
    return read


def _rule_counts(borders: Borders, points: np.ndarray, i: np.ndarray, leaf: np.ndarray, d2: np.ndarray, near, k: int) -> list[tuple]:
    """(rule, points, true neighbours, found, points with a wrong answer, leaves read) of both rules. ``i``, ``leaf``
    and ``d2`` are the true neighbours. A true neighbour is found if its leaf is read, as it is among the k nearest of
    any rows that it is in. The box rule reads the leaves whose tight box is within the last k-th distance: it goes by
    growing box distance, and a row that lowers the k-th distance isn't nearer than its own box."""
    t, n = borders.tree, len(points)
    kth = np.full(n, -np.inf)
    np.maximum.at(kth, i, d2)
    kth[np.bincount(i, minlength=n) < k] = np.inf
    boxed = np.bincount(t.leaves_within(points, kth)[0], minlength=n)
    read = boundary_walk(borders, points, near, k)
    out = []
    for rule, found, leaves in (("box", t.pair_distance2(points, i, leaf + t.leaves) <= kth[i], boxed), ("boundary_points", read[i, leaf], read.sum(1))):
        out.append((rule, n, len(i), int(found.sum()), len(np.unique(i[~found])), int(leaves.sum())))
    return out


_RULE_SCHEMA = "rule string, queries long, truth long, found long, wrong long, leaves long"


def rule_recall(queries: DataFrame, index: DataFrame, tree: KdTree, cols: list[str], k: int, key: str = "key") -> DataFrame:
    """(rule, queries, truth, found, wrong, leaves): what the two stopping rules find of the true k nearest of every
    query, summed. An index within HELD_BYTES is held by every worker; of a larger one each query gets the k nearest of
    all leaves within the bound of its home node (whose leaf is to have k rows), met by leaf as in ``knn_join``."""
    q, d = _as_queries(queries, cols, key), len(cols)
    step = max(64, 4_000_000 // tree.leaves)
    sum_up = lambda df: df.groupBy("rule").agg(*[F.sum(c).alias(c) for c in ("queries", "truth", "found", "wrong", "leaves")])
    give = lambda found: pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*found, strict=True)], names=[c.split()[0] for c in _RULE_SCHEMA.split(", ")])
    if int(tree.counts[1]) * 8 * (d + 2) <= HELD_BYTES:
        got = index.select("leaf", "key", *cols).toArrow()
        sent = q.sparkSession.sparkContext.broadcast((tree, got.combine_chunks()))

        def held_kernel(batches):
            t, table = sent.value
            borders, held = Borders(t), HeldIndex(t, table["leaf"].to_numpy(), table["key"].to_numpy(), np.stack([table[c].to_numpy() for c in cols], 1))
            for b in batches:
                x = np.stack([np.asarray(b.column(1 + j)) for j in range(d)], 1)
                x = x[np.argsort(t.locate(x), kind="stable")]
                for at in range(0, len(x), step):
                    own = x[at : at + step]

                    def near(leaf, some, own=own):
                        d2 = distances(own[some], held.x[held.start[leaf] : held.start[leaf + 1]])
                        return np.partition(d2, k - 1, axis=1)[:, :k] if d2.shape[1] > k else np.pad(d2, ((0, 0), (0, k - d2.shape[1])), constant_values=np.inf)

                    i, row, d2 = held.search(own, k)
                    yield give(_rule_counts(borders, own, i, np.searchsorted(held.start, row, "right") - 1, d2, near, k))

        return sum_up(q.mapInArrow(held_kernel, _RULE_SCHEMA))
    q = staged(q, "queries")
    points = index.select("leaf", "key", *cols)
    home = staged(_met(_leaf_lists(q.withColumn("bound", F.lit(float("inf"))), tree, d, k, True), points, cols, k, tell=True), "round1")
    bound = _ranked(home, k).groupBy("query_key").agg(F.max("d2").alias("m"), F.count("*").alias("n"))
    bounded = q.join(bound, "query_key", "left").withColumn("bound", F.when(F.col("n") >= k, F.col("m")).otherwise(F.lit(float("inf"))))
    near = home.unionByName(_met(_leaf_lists(bounded, tree, d, k, False), points, cols, k, tell=True))
    lists = near.groupBy("query_key").agg(F.collect_list(F.struct("d2", "key", "leaf")).alias("n")).join(q, "query_key")
    lists = lists.select(*[f"q{j}" for j in range(d)], *[F.col(f"n.{c}").alias(c) for c in ("d2", "key", "leaf")])
    sent_tree = q.sparkSession.sparkContext.broadcast(tree)

    def list_kernel(batches):
        borders = Borders(sent_tree.value)
        for whole in batches:
            for at in range(0, whole.num_rows, step):
                b = whole.slice(at, step)
                x, n = np.stack([np.asarray(b.column(j)) for j in range(d)], 1), b.num_rows
                i = np.repeat(np.arange(n), np.asarray(b.column(d).value_lengths()))
                d2, keys, leaf = (np.asarray(b.column(d + c).flatten()) for c in range(3))
                order = np.lexsort((d2, i, leaf))
                place, by_leaf = leaf[order] * n + i[order], d2[order]

                def near(leaf_, some, n=n, place=place, by_leaf=by_leaf):
                    a, e = np.searchsorted(place, leaf_ * n + some), np.searchsorted(place, leaf_ * n + some, "right")
                    at_ = a[:, None] + np.arange(k)
                    return np.where(at_ < e[:, None], by_leaf[np.minimum(at_, len(by_leaf) - 1)], np.inf)

                yield give(_rule_counts(borders, x, *first_k(i, d2, keys, k, (i, leaf, d2)), near, k))

    return sum_up(lists.mapInArrow(list_kernel, _RULE_SCHEMA))


def nearest_of_few(df: DataFrame, cols: list[str], table: pa.Table, features: list[str], give: list[str], keep: list[str]) -> DataFrame:
    """``keep`` columns of ``df``, the ``give`` columns of the nearest row of an in-memory ``table``, and d2: a pass
    over ``df`` that moves nothing. Ties go to the earlier row of the table; without rows there is no result."""
    from pyspark.sql.pandas.types import from_arrow_type

    sent = df.sparkSession.sparkContext.broadcast(table.combine_chunks())
    n = len(keep)

    def kernel(batches):
        t = sent.value
        y = np.stack([t[c].to_numpy() for c in features], 1) if t.num_rows else np.zeros((0, len(cols)))
        step = max(1, 2_000_000 // max(1, len(y)))
        for b in batches:
            if not b.num_rows or not len(y):
                continue
            x = np.stack([np.asarray(b.column(n + j)) for j in range(len(cols))], 1)
            at, d2 = np.zeros(len(x), np.int64), np.zeros(len(x))
            for a in range(0, len(x), step):
                m = distances(x[a : a + step], y)
                at[a : a + step] = m.argmin(1)
                d2[a : a + step] = m[np.arange(len(m)), at[a : a + step]]
            yield pa.RecordBatch.from_arrays([*b.columns[:n], *(t[c].combine_chunks().take(pa.array(at)) for c in give), pa.array(d2)], names=[*keep, *give, "d2"])

    kinds = {f.name: f.dataType.simpleString() for f in df.select(*keep).schema}
    schema = [f"`{c}` {kinds[c]}" for c in keep] + [f"`{c}` {from_arrow_type(table.schema.field(c).type).simpleString()}" for c in give]
    return df.select(*keep, *cols).mapInArrow(kernel, ", ".join([*schema, "d2 double"]))


def match_simulations(observed: DataFrame, sims: DataFrame, cols: list[str], params: list[str], count: int, levels: int | None = None) -> DataFrame:
    """(key, sim_id, *params, d2): the nearest simulated object of each observed one with the parameters it was made
    from, ties to the lower id. Up to HELD_BYTES of simulations are held by every worker; more are indexed by a kd-tree
    and joined by leaf."""
    if count * 8 * (len(cols) + len(params) + 1) <= HELD_BYTES:
        table = sims.select("sim_id", *cols, *params).orderBy("sim_id").toArrow()
        return nearest_of_few(observed, cols, table, cols, ["sim_id", *params], ["key"])
    from cellspace.operators.kdtree import build_kdtree

    index, tree = build_kdtree(sims.withColumnRenamed("sim_id", "key"), cols, levels, "hybrid")
    near = knn_join(observed, index, tree, cols, 1, carry=params)
    return near.select(F.col("query_key").alias("key"), F.col("key").alias("sim_id"), *params, "d2")


def knn_lsh(queries: DataFrame, points: DataFrame, cols: list[str], k: int, bucket: float, tables: int = 4) -> DataFrame:
    """Approximate baseline: random-projection buckets, then exact distances within them. Only the k nearest of a bucket
    leave it: they hold the k nearest of all buckets of the query."""
    rng = np.random.default_rng(5)
    rays = rng.standard_normal((tables, 2, len(cols)))
    shifts = rng.uniform(0, bucket, (tables, 2))

    def keys(prefix: str) -> Column:
        out = []
        for t in range(tables):
            parts = []
            for h in range(2):
                dot = F.lit(float(shifts[t, h]))
                for c, w in enumerate(rays[t, h]):
                    dot = dot + F.col(f"{prefix}{c}") * float(w)
                parts.append(F.floor(dot / bucket))
            out.append(F.xxhash64(F.lit(t), *parts))
        return F.array(*out)

    q = _as_queries(queries, cols, "key").withColumns({"bound": F.lit(float("inf")), "leaf": F.explode(keys("q"))})
    p = points.select("key", *[F.col(c).alias(f"p{k}") for k, c in enumerate(cols)]).withColumn("leaf", F.explode(keys("p")))
    near = _met(q, p, [f"p{k}" for k in range(len(cols))], k, 20_000)
    return _ranked(near.distinct(), k).select("query_key", "rank", "key", "d2")
