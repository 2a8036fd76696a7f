"""Level-of-detail scenes: sources and filters by configuration, asynchronous hand-over, a cache of scenes, and the
adaptive boxes, edges and cells in a view."""

from __future__ import annotations

import threading
from collections import OrderedDict
from collections.abc import Callable
from concurrent.futures import Future, ThreadPoolExecutor
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellspace.operators.grid import LayeredGrid, in_box, sample_box
from cellspace.operators.kdtree import KdTree


@dataclass(frozen=True)
class View:
    lo: tuple[float, ...]
    hi: tuple[float, ...]
    wanted: int

    def holds(self, other: View) -> bool:
        return all(a <= b for a, b in zip(self.lo, other.lo, strict=True)) and all(a >= b for a, b in zip(self.hi, other.hi, strict=True))


def initial_view(grid: LayeredGrid) -> View:
    """The global box with what the first layer holds."""
    return View(tuple(grid.lo), tuple(grid.hi), grid.base)


@dataclass
class SceneCache:
    """The last ``capacity`` scenes. A view is served from a scene that covers it if that scene has every row of its
    box, or enough rows in the view; zooming out to a scene still held costs nothing."""

    capacity: int = 8
    hits: int = 0
    misses: int = 0
    held: OrderedDict = field(default_factory=OrderedDict)

    def get(self, view: View, cols: list[str]):
        for old in reversed(list(self.held)):
            rows, complete = self.held[old]
            if old.holds(view):
                inside = [r for r in rows if all(a <= r[c] <= b for c, a, b in zip(cols, view.lo, view.hi, strict=True))]
                if complete or len(inside) >= view.wanted:
                    self.held.move_to_end(old)
                    self.hits += 1
                    return inside
        self.misses += 1
        return None

    def put(self, view: View, rows: list, complete: bool) -> None:
        self.held[view] = (rows, complete)
        self.held.move_to_end(view)
        while len(self.held) > self.capacity:
            self.held.popitem(last=False)


class SceneSource:
    """Serves views of a layered grid. ``mode='thread'``: ``show`` returns at once and ``poll`` never waits: it gives
    the newest finished scene once, or None while none is new. ``mode='inline'`` runs in the caller. A view that came
    later replaces one still running."""

    def __init__(self, grid: LayeredGrid, mode: str = "thread", cache: SceneCache | None = None, fetch: Callable[[View], tuple[list, bool]] | None = None):
        self.grid, self.mode, self.cache = grid, mode, cache or SceneCache()
        self.fetch = fetch or self._fetch
        self.pool = ThreadPoolExecutor(1) if mode == "thread" else None
        self.lock, self.ready, self.last, self.number = threading.Lock(), None, None, 0

    def _fetch(self, view: View) -> tuple[list, bool]:
        rows = sample_box(self.grid, view.lo, view.hi, view.wanted).collect()  # bounded by the view's number and a layer
        return rows, len(rows) < view.wanted

    def show(self, view: View) -> Future | None:
        self.number += 1
        mine = self.number
        if self.pool is None:
            self._run(view, mine)
            return None
        return self.pool.submit(self._run, view, mine)

    def _run(self, view: View, mine: int) -> None:
        if mine != self.number:
            return
        rows = self.cache.get(view, self.grid.cols)
        if rows is None:
            rows, complete = self.fetch(view)
            self.cache.put(view, rows, complete)
        with self.lock:
            if mine == self.number:
                self.ready = rows

    def poll(self):
        if not self.lock.acquire(blocking=False):
            return None
        try:
            out, self.ready = self.ready, None
            if out is not None:
                self.last = out
            return out
        finally:
            self.lock.release()

    def close(self) -> None:
        if self.pool is not None:
            self.pool.shutdown(wait=True)


PLUGINS: dict[str, Callable] = {}


def plugin(name: str):
    def add(f: Callable) -> Callable:
        PLUGINS[name] = f
        return f

    return add


@plugin("bounds")
def _bounds(scene: DataFrame, cols: list[str]) -> DataFrame:
    return scene.agg(*[f(c).alias(f"{t}_{c}") for c in cols for t, f in (("lo", F.min), ("hi", F.max))])


@plugin("thin")
def _thin(scene: DataFrame, keep: int) -> DataFrame:
    return scene.orderBy("rand_rank").limit(keep)


@plugin("box")
def _box(scene: DataFrame, cols: list[str], lo: list, hi: list) -> DataFrame:
    return scene.where(in_box(cols, lo, hi))


class SceneGraph:
    """Filters by configuration: [{"name": .., "input": .., "plugin": .., "options": {..}}, ..] with the source named
    "source". Stages start in order and are closed in reverse."""

    def __init__(self, config: list[dict]):
        unknown = [c["plugin"] for c in config if c["plugin"] not in PLUGINS]
        if unknown:
            raise KeyError(f"unknown plugins: {unknown}")
        self.config, self.state = config, "new"

    def start(self) -> None:
        self.state = "started"

    def stop(self) -> None:
        self.state = "stopped"

    def run(self, source: DataFrame) -> dict[str, DataFrame]:
        if self.state != "started":
            raise RuntimeError("start the graph first")
        out = {"source": source}
        for c in self.config:
            out[c["name"]] = PLUGINS[c["plugin"]](out[c["input"]], **c.get("options", {}))
        return out


def visible_boxes(tree: KdTree, view: View) -> tuple[int, np.ndarray]:
    """(height, heap nodes): the greatest height at which the wanted number of boxes meet the view, else the leaves."""
    lo, hi = np.array(view.lo), np.array(view.hi)
    for depth in range(tree.levels + 1):
        nodes = np.arange(1 << depth, 2 << depth)
        met = nodes[(tree.counts[nodes] > 0) & (tree.lo[nodes] <= hi).all(1) & (tree.hi[nodes] >= lo).all(1)]
        if len(met) >= view.wanted or depth == tree.levels:
            return tree.levels - depth, met
    raise AssertionError


def visible_edges(levels: list[tuple[np.ndarray, np.ndarray]], view: View) -> tuple[int, np.ndarray]:
    """(level, edges) of the first graph (coordinates, pairs) with enough edges that have an end in the view."""
    lo, hi = np.array(view.lo), np.array(view.hi)
    met = np.zeros((0, 2), int)
    for k, (x, pairs) in enumerate(levels):
        inside = ((x >= lo) & (x <= hi)).all(1)
        met = pairs[inside[pairs].any(1)] if len(pairs) else pairs
        if len(met) >= view.wanted or k + 1 == len(levels):
            return k, met
    return 0, met


def points_and_boxes(grid: LayeredGrid, tree: KdTree, view: View, boxes: int) -> DataFrame:
    """A sample of the view's points, each with the heap node of the box of the right size that it lies in, its height
    and rows: points and boxes of one scene."""
    height, nodes = visible_boxes(tree, View(view.lo, view.hi, boxes))
    points = sample_box(grid, view.lo, view.hi, view.wanted)
    from cellspace.operators.kdtree import locate_leaves

    keep = ["key", "layer"]
    found = locate_leaves(points, tree, grid.cols, keep)
    return found.select(*keep, F.shiftright(F.col("leaf") + tree.leaves, height).alias("node"), F.lit(height).alias("height"))


def coloured_cells(spark, seeds, edges: np.ndarray, counts: DataFrame, view: View) -> DataFrame:
    """(cell_tag, x.., neighbours, n, colour) of the cells whose seed is in the view: a cell is drawn from the edges to
    its neighbours, and coloured by its rows over the cube of its reach, from 0 (thin) to 255 (dense), by rank."""
    inside = ((seeds.x >= np.array(view.lo)) & (seeds.x <= np.array(view.hi))).all(1)
    near: dict[int, list[int]] = {}
    for a, b in edges:
        for i, j in ((int(a), int(b)), (int(b), int(a))):
            if inside[i]:
                near.setdefault(i, []).append(int(seeds.tags[j]))
    d = seeds.x.shape[1]
    data = [(int(seeds.tags[i]), *map(float, seeds.x[i]), sorted(near.get(int(i), []))) for i in np.flatnonzero(inside)]
    cells = spark.createDataFrame(data, "cell_tag long, " + ", ".join(f"x{k} double" for k in range(d)) + ", neighbours array<long>")
    dense = cells.join(counts, "cell_tag", "left").withColumn("n", F.coalesce("n", F.lit(0).cast("long")))
    dense = dense.withColumn("density", F.when(F.col("reach") > 0, F.col("n") / F.pow("reach", F.lit(float(d)))).otherwise(0.0))
    from pyspark.sql.window import Window

    colour = F.floor(F.percent_rank().over(Window.orderBy("density", "cell_tag")) * 255).cast("int")
    return dense.withColumn("colour", colour).drop("reach", "density")


def scene_from_sql(spark, text: str) -> DataFrame:
    """Points from a query with exactly three numeric columns, as x, y, z."""
    df = spark.sql(text)
    numeric = {"double", "float", "int", "bigint", "smallint", "tinyint"}
    kinds = [t for _, t in df.dtypes]
    if len(kinds) != 3 or any(t not in numeric and not t.startswith("decimal") for t in kinds):
        raise ValueError("a scene needs exactly three numeric columns")
    return df.select(*[F.col(f"`{c}`").cast("double").alias(n) for c, n in zip(df.columns, "xyz", strict=True)])
