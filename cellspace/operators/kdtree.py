"""Balanced kd-trees: rows get a leaf, the tree keeps the tight box and count of every node.

``rank`` splits every node at the middle row of its axis (ties by key), so leaf sizes differ by one at most. With axes
in turn, the upper levels find each middle row without a sort of the table: approximate quantiles bracket it, rows below
the bracket are counted and only those in it are ranked; then every upper node is finished by one task after one
shuffle. With axes chosen by the data all levels are upper ones.
``sketch`` splits at approximate medians of all nodes of a level from one aggregation, without any sort. ``hybrid``
cuts the upper levels by a bounded sample on the driver and ranks within the nodes below, so rows move once.
Leaf ordinals 0..L-1 are kept; post-order numbers follow in closed form.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cellspace.functions.shapes import INSIDE, OUTSIDE, PARTIAL, merge_runs
from cellspace.plans.shared import WINDOW_ROWS, row_numbers, staged


def leaf_levels(rows: int) -> int:
    """Splits so that leaves and rows of a leaf are about the square root of the rows."""
    return max(0, int(round(np.log2(max(rows, 1)) / 2)))


def postorder_leaf(j: int) -> int:
    """Post-order number (from 1) of leaf ``j``."""
    return 2 * j - bin(j).count("1") + 1


def postorder_column(j: str) -> Column:
    return (F.col(j) * 2 - F.bit_count(F.col(j)) + 1).cast("long")


def node_table(levels: int) -> list[tuple[int, int, int, int, int]]:
    """(node id, height, first leaf, last leaf, first post-order id below) of all nodes."""
    out = []
    for h in range(levels + 1):
        for n in range(1 << (levels - h)):
            first, last = n << h, ((n + 1) << h) - 1
            node = postorder_leaf(last) + h
            out.append((node, h, first, last, node - (1 << (h + 1)) + 2))
    return out


@dataclass
class KdTree:
    """Arrays in heap order: node 1 is the root, 2n and 2n+1 its children, leaf j is node L + j."""

    levels: int
    axes: np.ndarray
    lo: np.ndarray
    hi: np.ndarray
    counts: np.ndarray
    region_lo: np.ndarray | None = None
    region_hi: np.ndarray | None = None

    @property
    def leaves(self) -> int:
        return 1 << self.levels

    @property
    def dim(self) -> int:
        return self.lo.shape[1]

    def leaf_boxes(self) -> tuple[np.ndarray, np.ndarray]:
        return self.lo[self.leaves :], self.hi[self.leaves :]

    def cover(self, shape) -> tuple[list[tuple[int, int]], list[tuple[int, int]], dict]:
        """(leaf intervals wholly inside, leaf intervals to test, counts): descends only below partial nodes."""
        inside, partial, visited = [], [], 0
        front = np.array([1])
        totals = {"inside": 0, "partial": 0, "outside": 0, "rows_inside": 0, "rows_partial": 0}
        while len(front):
            front = front[self.counts[front] > 0]
            visited += len(front)
            kind = shape.classify(self.lo[front], self.hi[front]) if len(front) else np.zeros(0)
            depth = np.frexp(front.astype(float))[1] - 1
            for n, k, dep in zip(front, kind, depth, strict=True):
                h = self.levels - int(dep)
                first = (int(n) << h) - self.leaves
                if k == INSIDE:
                    inside.append((first, first + (1 << h) - 1))
                    totals["inside"] += 1 << h
                    totals["rows_inside"] += int(self.counts[n])
                elif k == PARTIAL and h == 0:
                    partial.append(first)
                    totals["partial"] += 1
                    totals["rows_partial"] += int(self.counts[n])
            open_nodes = front[(kind == PARTIAL) & (depth < self.levels)] if len(front) else front
            front = np.concatenate([open_nodes * 2, open_nodes * 2 + 1]) if len(open_nodes) else open_nodes
        totals["outside"] = self.leaves - totals["inside"] - totals["partial"]
        totals["visited"] = visited
        runs = merge_runs(sorted(j for a, b in inside for j in range(a, b + 1)))
        return runs, merge_runs(sorted(partial)), totals

    def box_distance2(self, points: np.ndarray, nodes: np.ndarray) -> np.ndarray:
        """Squared distances [points, nodes] to tight boxes; empty nodes are infinitely far."""
        d = np.zeros((len(points), len(nodes)))
        for k in range(self.dim):
            gap = np.maximum(self.lo[nodes, k][None] - points[:, k, None], points[:, k, None] - self.hi[nodes, k][None])
            d += np.maximum(gap, 0) ** 2
        d[:, self.counts[nodes] == 0] = np.inf
        return d

    def pair_distance2(self, points: np.ndarray, i: np.ndarray, nodes: np.ndarray) -> np.ndarray:
        """Squared distances of ``points[i]`` to the tight boxes of ``nodes``, pair by pair."""
        d = np.zeros(len(i))
        for k in range(self.dim):
            x = points[i, k]
            d += np.maximum(np.maximum(self.lo[nodes, k] - x, x - self.hi[nodes, k]), 0) ** 2
        return d

    def leaves_within(self, points: np.ndarray, bound: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(point, leaf) pairs of all leaves with rows whose box is within the point's squared ``bound``, by descent."""
        i, node = np.arange(len(points)), np.ones(len(points), np.int64)
        for _ in range(self.levels + 1):
            near = (self.counts[node] > 0) & (self.pair_distance2(points, i, node) <= bound[i])
            i, node = i[near], node[near]
            if not len(i) or node[0] >= self.leaves:
                break
            i, node = np.repeat(i, 2), np.stack([2 * node, 2 * node + 1], 1).ravel()
        return i, node - self.leaves

    def leaf_range(self, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """First leaf and end leaf of nodes."""
        h = self.levels - (np.frexp(nodes.astype(float))[1] - 1)
        return (nodes << h) - self.leaves, ((nodes + 1) << h) - self.leaves

    def locate(self, points: np.ndarray) -> np.ndarray:
        """Leaf ordinals; a point goes left if it isn't beyond the left child's greatest coordinate on the axis."""
        node = np.ones(len(points), np.int64)
        for _ in range(self.levels):
            axis = self.axes[node]
            cut = self.hi[2 * node, axis]
            node = 2 * node + (points[np.arange(len(points)), axis] > cut)
        return node - self.leaves

    def home(self, points: np.ndarray, least: int) -> np.ndarray:
        """Heap nodes: the leaf of each point, or its nearest ancestor with ``least`` rows."""
        node = self.locate(points) + self.leaves
        for _ in range(self.levels):
            small = (self.counts[node] < least) & (node > 1)
            node = np.where(small, node >> 1, node)
        return node


def _roll_up(levels: int, lo: np.ndarray, hi: np.ndarray, counts: np.ndarray):
    L, d = 1 << levels, lo.shape[1]
    LO, HI, N = np.full((2 * L, d), np.inf), np.full((2 * L, d), -np.inf), np.zeros(2 * L, np.int64)
    LO[L:], HI[L:], N[L:] = lo, hi, counts
    for n in range(L - 1, 0, -1):
        LO[n], HI[n], N[n] = np.minimum(LO[2 * n], LO[2 * n + 1]), np.maximum(HI[2 * n], HI[2 * n + 1]), N[2 * n] + N[2 * n + 1]
    return LO, HI, N


def tree_from_leaves(indexed: DataFrame, cols: list[str], levels: int, axes: np.ndarray | None = None) -> KdTree:
    """Tight boxes by one aggregation over leaves (at most 2**20 rows reach the driver), rolled up in memory."""
    if levels > 20:
        raise ValueError("keep a tree of more than 2**20 leaves as a table")
    L, d = 1 << levels, len(cols)
    lo, hi, n = np.full((L, d), np.inf), np.full((L, d), -np.inf), np.zeros(L, np.int64)
    aggs = [f(c).alias(f"{t}{k}") for k, c in enumerate(cols) for t, f in (("a", F.min), ("b", F.max))]
    got = indexed.groupBy("leaf").agg(F.count("*").alias("n"), *aggs).toArrow()
    j = got["leaf"].to_numpy()
    n[j] = got["n"].to_numpy()
    for k in range(d):
        lo[j, k], hi[j, k] = got[f"a{k}"].to_numpy(), got[f"b{k}"].to_numpy()
    if axes is None:
        depth = np.frexp(np.maximum(np.arange(2 * L), 1).astype(float))[1] - 1
        axes = depth % d
    tree = KdTree(levels, axes, *_roll_up(levels, lo, hi, n))
    tree.region_lo, tree.region_hi = regions(tree)
    return tree


def regions(tree: KdTree) -> tuple[np.ndarray, np.ndarray]:
    """Partition boxes of all nodes in heap order: unlike tight boxes they fill the root's box. A node is cut where its
    left part ends (at its own border if that part is empty), as ``locate`` does."""
    lo, hi = np.repeat(tree.lo[1][None], 2 * tree.leaves, 0), np.repeat(tree.hi[1][None], 2 * tree.leaves, 0)
    for level in range(tree.levels):
        n = np.arange(1 << level, 2 << level)
        axis = tree.axes[n]
        cut = np.where(tree.counts[2 * n] > 0, tree.hi[2 * n, axis], lo[n, axis])
        for child in (2 * n, 2 * n + 1):
            lo[child], hi[child] = lo[n], hi[n]
        hi[2 * n, axis] = lo[2 * n + 1, axis] = cut
    return lo, hi


def _axis_column(axis_of_node: dict[int, int] | None, level: int, cols: list[str], node: str = "node") -> Column:
    if not axis_of_node:
        return F.col(cols[level % len(cols)])
    return F.element_at(F.array(*cols), F.element_at(F.create_map(*[F.lit(v) for kv in axis_of_node.items() for v in kv]), F.col(node)) + 1) if len(set(axis_of_node.values())) > 1 else F.col(cols[next(iter(axis_of_node.values()))])


def _choose_axes(df: DataFrame, cols: list[str], rule: str) -> dict[int, int] | None:
    """Axis by node: widest side or greatest variance."""
    if rule == "cycle":
        return None
    f = (lambda c: F.max(c) - F.min(c)) if rule == "widest" else F.var_pop
    rows = df.groupBy("node").agg(*[f(c).alias(f"v{k}") for k, c in enumerate(cols)]).collect()
    return {r["node"]: int(np.argmax([r[f"v{k}"] or 0 for k in range(len(cols))])) for r in rows}


def build_kdtree(df: DataFrame, cols: list[str], levels: int | None = None, method: str = "rank", axis_rule: str = "cycle", key: str = "key", sample_rows: int = 200_000, write: bool = True) -> tuple[DataFrame, KdTree]:
    """``df`` with ``leaf`` (ordinal) and ``leaf_id`` (post-order number), and the tree.

    Fewer rows than leaves leave some empty; an empty table gives an empty tree. Without ``write`` no copy of the rows is
    written: the index is a plan over ``df``, which had better be a written table.
    """
    rows = df.count()
    levels = leaf_levels(rows) if levels is None else levels
    if method == "hybrid":
        return _build_hybrid(df, cols, levels, rows, key, sample_rows, write)
    if method == "rank":
        return _build_exact(df, cols, levels, rows, key, NODE_ROWS, axis_rule, write)
    axes = np.zeros(2 << levels, np.int64)
    out = df.withColumn("node", F.lit(1).cast("long"))
    for level in range(levels):
        out = out.withColumn("__axis", _axis_column(_axes_of_level(out, cols, axis_rule, level, axes), level, cols))
        cuts = staged(out.groupBy("node").agg(F.percentile_approx("__axis", 0.5, 2000).alias("__last")), "cuts")
        out = out.join(F.broadcast(cuts), "node", "left").withColumn("node", F.col("node") * 2 + (F.col("__axis") > F.col("__last")).cast("long")).drop("__last", "__axis")
        if write and (level % 4 == 3 or axis_rule != "cycle"):
            out = staged(out, "kd-level")
    return _indexed(out, cols, levels, axes, write)


def _axes_of_level(df: DataFrame, cols: list[str], rule: str, level: int, axes: np.ndarray) -> dict[int, int] | None:
    """Axis by node, also put into ``axes``; none where they come in turn."""
    chosen = _choose_axes(df, cols, rule)
    for n in range(1 << level, 2 << level):
        axes[n] = level % len(cols) if chosen is None else chosen.get(n, 0)
    return chosen


def _indexed(df: DataFrame, cols: list[str], levels: int, axes: np.ndarray | None, write: bool) -> tuple[DataFrame, KdTree]:
    """Rows with a leaf's ``node``, or with ``leaf`` and ``leaf_id``, as index and tree."""
    if "node" in df.columns:
        df = df.withColumn("leaf", (F.col("node") - (1 << levels)).cast("long")).drop("node").withColumn("leaf_id", postorder_column("leaf"))
    out = staged(df, "kd") if write else df
    return out, tree_from_leaves(out, cols, levels, axes)


#: Rows of an upper node that one task finishes.
NODE_ROWS = 1_000_000


def _middle_rows(df: DataFrame, axis: str, key: str) -> list[tuple]:
    """(node, axis value, key) of the middle row of every node: the ceil(n / 2)-th by (axis, key)."""
    spark = df.sparkSession
    share = F.percentile_approx(axis, F.array(F.lit(0.4995), F.lit(0.5005)), 10_000)
    spans = [(r["node"], float(r["q"][0]), float(r["q"][1]), r["n"]) for r in df.groupBy("node").agg(share.alias("q"), F.count("*").alias("n")).collect()]
    out: list[tuple] = []
    while spans:
        table = F.broadcast(spark.createDataFrame(spans, "node long, __lo double, __hi double, __n long"))
        marked = df.select("node", F.col(axis).alias("__v"), F.col(key).alias("__k")).join(table, "node")
        inside = staged(marked.where((F.col("__v") >= F.col("__lo")) & (F.col("__v") <= F.col("__hi"))).select("node", "__v", "__k", "__n"), "bracket")
        below = {r["node"]: r["b"] for r in marked.groupBy("node").agg(F.count_if(F.col("__v") < F.col("__lo")).alias("b")).collect()}
        ranked = row_numbers(inside, ["node", "__v", "__k"], "__r", inside.count())
        first = ranked.groupBy("node").agg(F.min("__r").alias("__first"))
        before = spark.createDataFrame(list(below.items()), "node long, __below long")
        at = ranked.join(F.broadcast(first), "node").join(F.broadcast(before), "node").where(F.col("__r") - F.col("__first") + 1 + F.col("__below") == F.ceil(F.col("__n") / 2))
        found = [(r["node"], r["__v"], r["__k"]) for r in at.select("node", "__v", "__k").collect()]
        out += found
        done = {n for n, _, _ in found}
        spans = [(n, -float("inf"), float("inf"), c) for n, _, _, c in spans if n not in done]  # a bracket that missed
    return out


def _build_exact(df: DataFrame, cols: list[str], levels: int, rows: int, key: str, node_rows: int = NODE_ROWS, axis_rule: str = "cycle", write: bool = True) -> tuple[DataFrame, KdTree]:
    """The rank build: upper levels by middle rows, the rest of each upper node in one task. With axes chosen by the
    data all levels go by middle rows."""
    cycle = axis_rule == "cycle"
    top = min(levels, int(np.ceil(np.log2(max(1, rows / node_rows))))) if cycle else levels
    axes = np.zeros(2 << levels, np.int64)
    out = df.withColumn("node", F.lit(1).cast("long"))
    if top and write:
        out = staged(out, "kd-rows")
    key_type = df.schema[key].dataType.simpleString()
    for level in range(top):
        out = out.withColumn("__axis", _axis_column(_axes_of_level(out, cols, axis_rule, level, axes), level, cols))
        cuts = df.sparkSession.createDataFrame(_middle_rows(out, "__axis", key), f"node long, __v double, __k {key_type}")
        right = (F.col("__axis") > F.col("__v")) | ((F.col("__axis") == F.col("__v")) & (F.col(key) > F.col("__k")))
        out = out.join(F.broadcast(cuts), "node").withColumn("node", F.col("node") * 2 + right.cast("long")).drop("__axis", "__v", "__k")
        if write and not cycle and level % 4 == 3:
            out = staged(out, "kd-level")
    if top == levels:
        return _indexed(out.select(*df.columns, "node"), cols, levels, None if cycle else axes, write)
    names, d = [c for c in out.columns if c != "node"], len(cols)

    def finish(table: pa.Table) -> pa.Table:
        x = [table[c].to_numpy() for c in cols]
        order = np.argsort(table[key].to_numpy(zero_copy_only=False), kind="stable")
        leaf = np.empty(len(order), np.int64)
        parts = [(int(table["node"][0].as_py()), order)]  # rows of a node, by key
        for level in range(top, levels):
            v, below = x[level % d], []
            for node, own in parts:
                side = np.zeros(len(v), bool)
                side[own[np.argsort(v[own], kind="stable")][: -(-len(own) // 2)]] = True
                left = side[own]
                below += [(2 * node, own[left]), (2 * node + 1, own[~left])]
            parts = below
        for node, own in parts:
            leaf[own] = node - (1 << levels)
        return table.select(names).append_column("leaf", pa.array(leaf)).append_column("leaf_id", pa.array(2 * leaf - np.bitwise_count(leaf.astype(np.uint64)).astype(np.int64) + 1))

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in out.schema if f.name != "node") + ", leaf long, leaf_id long"
    return _indexed(out.groupBy("node").applyInArrow(finish, schema), cols, levels, None, write)


def sample_cuts(points: np.ndarray, levels: int) -> np.ndarray:
    """Cut values in heap order of an in-memory tree over a sample, axes in turn."""
    cuts = np.zeros(1 << levels)
    nodes = {1: points}
    for level in range(levels):
        below = {}
        for n, p in nodes.items():
            axis = level % points.shape[1]
            cuts[n] = np.median(p[:, axis]) if len(p) else 0.0
            left = p[:, axis] <= cuts[n]
            below[2 * n], below[2 * n + 1] = p[left], p[~left]
        nodes = below
    return cuts


def _build_hybrid(df: DataFrame, cols: list[str], levels: int, rows: int, key: str, sample_rows: int, write: bool = True) -> tuple[DataFrame, KdTree]:
    """Upper cuts from a bounded sample; below, each upper node is ranked in windows after one shuffle."""
    top = max(0, min(levels, int(np.ceil(np.log2(max(1, rows / WINDOW_ROWS * 4)))), 12))
    top = max(top, min(levels, 3))
    share = min(1.0, sample_rows / max(rows, 1))
    sample = df.where(F.pmod(F.xxhash64(key), F.lit(1_000_000)) < int(share * 1_000_000)).select(*cols).toArrow()
    pts = np.stack([sample[c].to_numpy() for c in cols], 1) if sample.num_rows else np.zeros((0, len(cols)))
    cuts = sample_cuts(pts, top)
    node = F.lit(1).cast("long")
    for level in range(top):
        cut = F.element_at(F.array(*[F.lit(float(c)) for c in cuts[: 1 << (level + 1)]]), node.cast("int") + 1)
        node = node * 2 + (F.col(cols[level % len(cols)]) > cut).cast("long")
    out = df.withColumn("node", node)
    if write and top < levels:
        out = staged(out, "kd-top")
    for level in range(top, levels):
        w = Window.partitionBy("node")
        right = F.row_number().over(w.orderBy(cols[level % len(cols)], key)) > F.ceil(F.count("*").over(w) / 2)
        out = out.withColumn("__right", right).withColumn("node", F.col("node") * 2 + F.col("__right").cast("long")).drop("__right")
        if write and level % 4 == 3:
            out = staged(out, "kd-level")
    return _indexed(out, cols, levels, None, write)


def locate_leaves(points: DataFrame, tree: KdTree, cols: list[str], keep: list[str]) -> DataFrame:
    """``keep`` columns and ``leaf`` of each point, by descent through a broadcast tree in Arrow batches."""
    sent = points.sparkSession.sparkContext.broadcast(tree)
    schema = points.select(*keep).schema

    def kernel(batches):
        for b in batches:
            x = np.stack([np.asarray(b.column(len(keep) + k)) for k in range(len(cols))], 1)
            yield pa.RecordBatch.from_arrays([*b.columns[: len(keep)], pa.array(sent.value.locate(x))], names=[*keep, "leaf"])

    return points.select(*keep, *cols).mapInArrow(kernel, ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in schema) + ", leaf long")


def box_elongation(tree: KdTree) -> np.ndarray:
    """Longest over shortest side of each leaf's tight box (sides of no length count as a millionth of the root's)."""
    lo, hi = tree.leaf_boxes()
    some = tree.counts[tree.leaves :] > 0
    side = np.maximum((hi - lo)[some], 1e-6 * (tree.hi[1] - tree.lo[1])[None])
    return side.max(1) / side.min(1)


def rank_build_sql(space_sql: str, dim: int, levels: int) -> str:
    """The rank build as plain SQL: a chain of windows, one for each level; columns key, x.., leaf."""
    ctes = [f"t0 AS (SELECT *, CAST(0 AS BIGINT) AS node FROM ({space_sql}))"]
    for level in range(levels):
        axis = f"x{level % dim}"
        ctes.append(f"t{level + 1} AS (SELECT * EXCLUDE (node), node * 2 + CASE WHEN row_number() OVER (PARTITION BY node ORDER BY {axis}, key) > ceil(count(*) OVER (PARTITION BY node) / 2.0) THEN 1 ELSE 0 END AS node FROM t{level})")
    return "WITH " + ", ".join(ctes) + f", kd AS (SELECT * EXCLUDE (node), node AS leaf FROM t{levels})"


def recursive_leaves(df: DataFrame, cols: list[str], levels: int, key: str = "key") -> DataFrame:
    """The same leaves by recursion on nodes: a plan branch for each node, for small tables and comparison only."""

    def split(part: DataFrame, level: int, leaf: int) -> DataFrame:
        if level == levels:
            return part.withColumn("leaf", F.lit(leaf).cast("long"))
        w = Window.orderBy(cols[level % len(cols)], key)
        part = part.withColumn("__r", F.row_number().over(w)).withColumn("__n", F.count("*").over(Window.partitionBy()))
        left, right = F.col("__r") <= F.ceil(F.col("__n") / 2), F.col("__r") > F.ceil(F.col("__n") / 2)
        return split(part.where(left).drop("__r", "__n"), level + 1, 2 * leaf).unionByName(split(part.where(right).drop("__r", "__n"), level + 1, 2 * leaf + 1))

    return split(df, 0, 0)


__all__ = ["INSIDE", "OUTSIDE", "PARTIAL", "KdTree", "build_kdtree"]
