"""Random ranks, the layered uniform grid and progressive samples inside a box, with the sampling baselines.

Rows get a random rank; layer l holds the next base * 2**(d*(l-1)) ranks and cuts the global box into 2**l cells an
axis, so a cell holds base / 2**d rows on average in every layer. A request walks the layers from the first until the
rows found reach the wanted number; every prefix of layers is a uniform sample of the box.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cellspace.plans.shared import maybe_broadcast, row_numbers, staged

BASE = 1024


def rank_hash(key: str = "key", seed: int = 7) -> Column:
    return F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(str(seed)), F.col(key))), 1, 15), 16, 10).cast("long")


def rank_hash_sql(key: str = "key", seed: int = 7) -> str:
    return f"CAST('0x' || substr(md5(concat_ws('|', '{seed}', {key})), 1, 15) AS BIGINT)"


def assign_random_rank(df: DataFrame, key: str = "key", seed: int = 7, how: str = "exact", rows: int | None = None) -> DataFrame:
    """``rand_rank`` 1..N. ``exact`` is a dense permutation; ``hash`` places the hash in 1..N without any sort."""
    if how == "hash":
        n = df.count() if rows is None else rows
        return df.withColumn("rand_rank", (F.floor(rank_hash(key, seed) / F.lit(float(1 << 60)) * n) + 1).cast("long"))
    out = df.withColumn("__h", rank_hash(key, seed))
    return row_numbers(out, ["__h", key], "rand_rank", rows).drop("__h")


def layer_ends(base: int, d: int, rows: int) -> list[int]:
    """Last ranks of layers 1, 2, ... until all rows are covered; integers only."""
    ends, size, total = [], base, 0
    while not ends or total < rows:
        total += size
        ends.append(total)
        size <<= d
    return ends


def layer_of(rank: Column, base: int, d: int, rows: int) -> Column:
    ends = layer_ends(base, d, rows)
    out = F.lit(len(ends))
    for k in range(len(ends) - 1, 0, -1):
        out = F.when(rank <= ends[k - 1], F.lit(k)).otherwise(out)
    return out


def layer_sql(rank: str, base: int, d: int, rows: int) -> str:
    ends = layer_ends(base, d, rows)
    return "CASE " + " ".join(f"WHEN {rank} <= {e} THEN {k + 1}" for k, e in enumerate(ends)) + " END"


def cell_of(cols: list[str], layer: Column, lo, hi) -> Column:
    """Row-major cell number; coordinates on or beyond the upper edge fall into the last cell."""
    per_axis = F.pow(F.lit(2.0), layer).cast("long")
    out = F.lit(0).cast("long")
    for c, a, b in zip(cols, lo, hi, strict=True):
        span = float(b) - float(a)
        t = F.floor((F.col(c) - float(a)) / (span if span else 1.0) * per_axis)
        out = out * per_axis + F.greatest(F.lit(0), F.least(t, per_axis - 1))
    return out


def cell_sql(cols: list[str], layer: str, lo, hi) -> str:
    out = "0"
    for c, a, b in zip(cols, lo, hi, strict=True):
        span = float(b) - float(a) or 1.0
        out = f"(({out}) * power(2, {layer}) + greatest(0, least(floor(({c} - CAST({float(a)!r} AS DOUBLE)) / CAST({span!r} AS DOUBLE) * power(2, {layer})), power(2, {layer}) - 1)))"
    return f"CAST({out} AS BIGINT)"


@dataclass
class LayeredGrid:
    rows: DataFrame
    cols: list[str]
    base: int
    lo: list[float]
    hi: list[float]
    count: int

    @property
    def layers(self) -> int:
        return len(layer_ends(self.base, len(self.cols), self.count))

    def cells_meeting(self, layer: int, lo, hi) -> list[tuple[int, int]]:
        """Cell-number intervals (runs along the last axis) of a layer that meet a box."""
        per = 1 << layer
        spans = []
        for a, b, l, h in zip(self.lo, self.hi, lo, hi, strict=True):
            w = (b - a) or 1.0
            spans.append((max(0, min(per - 1, int(np.floor((l - a) / w * per)))), max(0, min(per - 1, int(np.floor((h - a) / w * per))))))
        starts = [0]
        for s, e in spans[:-1]:
            starts = [x * per + k for x in starts for k in range(s, e + 1)]
        return [(x * per + spans[-1][0], x * per + spans[-1][1]) for x in starts]


def global_box(df: DataFrame, cols: list[str]) -> tuple[list[float], list[float], int]:
    r = df.agg(F.count("*").alias("n"), *[f(c).alias(f"{t}{k}") for k, c in enumerate(cols) for t, f in (("a", F.min), ("b", F.max))]).first()
    d = range(len(cols))
    return [r[f"a{k}"] if r[f"a{k}"] is not None else 0.0 for k in d], [r[f"b{k}"] if r[f"b{k}"] is not None else 1.0 for k in d], r["n"]


def build_layered_grid(df: DataFrame, cols: list[str], base: int = BASE, key: str = "key", seed: int = 7, how: str = "exact") -> LayeredGrid:
    """Adds rand_rank, layer and cell_id; laid out by (layer, cell) in the shared folder."""
    lo, hi, n = global_box(df, cols)
    out = assign_random_rank(df, key, seed, how, n)
    out = out.withColumn("layer", layer_of(F.col("rand_rank"), base, len(cols), n))
    out = out.withColumn("cell_id", cell_of(cols, F.col("layer"), lo, hi))
    out = staged(out.repartitionByRange("layer", "cell_id").sortWithinPartitions("layer", "cell_id"), "grid")
    return LayeredGrid(out, cols, base, lo, hi, n)


def in_box(cols: list[str], lo, hi) -> Column:
    out = F.lit(True)
    for c, a, b in zip(cols, lo, hi, strict=True):
        out = out & F.col(c).between(float(a), float(b))
    return out


def read_layer(grid: LayeredGrid, layer: int, lo, hi) -> DataFrame:
    """Rows of a layer inside the box; the cell condition prunes the clustered layout, the box test is exact."""
    runs = grid.cells_meeting(layer, lo, hi)
    cells = F.lit(True)
    if len(runs) <= 200:
        cells = F.lit(False)
        for a, b in runs:
            cells = cells | F.col("cell_id").between(a, b)
    else:
        cells = F.col("cell_id").between(runs[0][0], runs[-1][1])
    return grid.rows.where((F.col("layer") == layer) & cells & in_box(grid.cols, lo, hi))


def iter_sample_box(grid: LayeredGrid, lo, hi, n: int) -> Iterator[DataFrame]:
    """Layer by layer until the rows seen reach ``n``: the first is there before the second is read."""
    seen = 0
    for layer in range(1, grid.layers + 1):
        rows = read_layer(grid, layer, lo, hi)
        yield rows
        seen += rows.count()
        if seen >= n:
            return


def sample_box(grid: LayeredGrid, lo, hi, n: int, trim: bool = False) -> DataFrame:
    """At least n rows of the box (all if it has fewer), from as few layers as possible; ``trim`` keeps the n of least
    rank, still a uniform sample."""
    out = None
    for rows in iter_sample_box(grid, lo, hi, n):
        out = rows if out is None else out.unionByName(rows)
    return out.orderBy("rand_rank").limit(n) if trim else out


def requests_frame(spark, requests: list[tuple[int, list[float], list[float], int]]) -> DataFrame:
    return spark.createDataFrame([(i, [float(v) for v in lo], [float(v) for v in hi], n) for i, lo, hi, n in requests], "request_id int, lo array<double>, hi array<double>, wanted int")


def _met_cells(grid: LayeredGrid, requests: DataFrame, layer: int) -> DataFrame:
    """A row for each request and each cell of the layer that its box meets."""
    per, out, cell = 1 << layer, requests, F.lit(0).cast("long")
    for k, (a, b) in enumerate(zip(grid.lo, grid.hi, strict=True)):
        at = lambda c, a=a, b=b, k=k: F.least(F.greatest(F.floor((F.col(c)[k] - a) / ((b - a) or 1.0) * per), F.lit(0)), F.lit(per - 1)).cast("long")
        out = out.where((F.col("hi")[k] >= a) & (F.col("lo")[k] <= b) & (F.col("lo")[k] <= F.col("hi")[k])).withColumn(f"__c{k}", F.explode(F.sequence(at("lo"), at("hi"))))
        cell = cell * per + F.col(f"__c{k}")
    return out.withColumn("cell_id", cell).drop(*[f"__c{k}" for k in range(len(grid.cols))])


def sample_boxes(grid: LayeredGrid, requests: DataFrame, count: int) -> DataFrame:
    """Many requests at once: (request_id, wanted, layer, last_layer, rows..) of all layers up to each request's last one.

    Layer by layer, requests that aren't full yet are turned into the cells they meet and joined to that layer's rows by
    cell, so deep layers are read only for requests that need them, and no row meets a box it isn't near. Cells of an
    open request are about as many as the rows it still wants.
    """
    box = F.lit(True)
    for k, c in enumerate(grid.cols):
        box = box & (F.col(c) >= F.col("lo")[k]) & (F.col(c) <= F.col("hi")[k])
    still, found = requests.select("request_id", "lo", "hi", "wanted", F.lit(0).cast("long").alias("seen")), None
    for layer in range(1, grid.layers + 1):
        cells = staged(_met_cells(grid, still, layer), "met")
        rows = grid.rows.where(F.col("layer") == layer)
        hit = rows.join(maybe_broadcast(cells, cells.count()), "cell_id").where(box).drop("lo", "hi", "seen")
        hit = staged(hit, "hits")
        found = hit if found is None else found.unionByName(hit)
        per = hit.groupBy("request_id").agg(F.count("*").alias("n"))
        still = still.join(per, "request_id", "left").withColumn("seen", F.col("seen") + F.coalesce("n", F.lit(0))).drop("n").where(F.col("seen") < F.col("wanted"))
        still = staged(still, "open")
        if layer == grid.layers or not still.limit(1).count():
            break
    last = found.groupBy("request_id").agg(F.max("layer").alias("last_layer"))
    return found.join(maybe_broadcast(last, count), "request_id")


def row_sample_top(df: DataFrame, percent: float, n: int, cols, lo, hi, seed: int = 3) -> DataFrame:
    """Baseline: Bernoulli row sample, then the first n rows in the box. Reads the whole table."""
    return df.sample(fraction=percent / 100, seed=seed).where(in_box(cols, lo, hi)).limit(n)


def block_layout(df: DataFrame, order: str, blocks: int = 100) -> DataFrame:
    """``df`` in about ``blocks`` files that are runs of ``order``, with the file's number as ``block``."""
    out = staged(df.repartitionByRange(blocks, order), "blocks")
    return out.withColumn("block", F.regexp_extract(F.col("_metadata.file_name"), r"part-(\d+)", 1).cast("int"))


def block_sample_top(layout: DataFrame, percent: float, n: int, cols, lo, hi, seed: int = 3) -> DataFrame:
    """Baseline: whole blocks by hash of their number, then the first n rows in the box.

    Biased where position in the table goes with a coordinate, and short of n where the percentage is too small.
    """
    chosen = F.pmod(F.xxhash64("block", F.lit(seed)), F.lit(1000)) < int(percent * 10)
    return layout.where(chosen & in_box(cols, lo, hi)).drop("block").limit(n)


def scan_sample_top(df: DataFrame, n: int, cols, lo, hi, rank: str = "rand_rank") -> DataFrame:
    """Baseline: scan, order by random rank, first n. Unbiased, reads everything."""
    return df.where(in_box(cols, lo, hi)).orderBy(rank).limit(n)


def tune_percent(n: int, rows: int, box_fraction: float) -> float:
    """Percentage of rows for about n rows of a box that holds ``box_fraction`` of the table; at most 100."""
    return min(100.0, 100.0 * n / max(1e-12, rows * box_fraction))


def ks_distance(sample: DataFrame, whole: DataFrame, col: str, steps: int = 10_000) -> float:
    """Greatest gap between the two distribution functions of a column, at the sample's values and at ``steps``
    quantiles of the whole; counts below each are taken by one aggregation over cut positions, without any sort."""
    cuts = whole.agg(F.percentile_approx(col, F.array(*[F.lit(k / 200) for k in range(201)]), steps).alias("q")).first()["q"]
    own = sample.agg(F.percentile_approx(col, F.array(*[F.lit(k / 200) for k in range(201)]), steps).alias("q")).first()["q"]
    if not cuts or not own:
        return 1.0
    edges = np.unique(np.array([*cuts, *own], float))
    below = []
    for df in (sample, whole):
        at = F.array_position(F.array(*[F.lit(float(e)) for e in edges]), F.col(col))  # a value on an edge belongs to it
        slot = F.when(at > 0, at - 1).otherwise(F.size(F.filter(F.array(*[F.lit(float(e)) for e in edges]), lambda e: e < F.col(col))))
        got = np.zeros(len(edges) + 1)
        for r in df.groupBy(slot.cast("int").alias("s")).count().collect():
            got[r["s"]] = r["count"]
        below.append(np.cumsum(got)[:-1] / max(1, got.sum()))
    return float(np.abs(below[0] - below[1]).max())


def chi_square(sample: DataFrame, whole: DataFrame, cols: list[str], lo, hi, bins: int = 4) -> tuple[float, int]:
    """(chi-square over degrees of freedom, occupied bins) of a sample's counts in equal bins of a box against the
    counts expected from the whole: about 1 for a fair sample."""
    cell = F.lit(0)
    for c, a, b in zip(cols, lo, hi, strict=True):
        cell = cell * bins + F.least(F.greatest(F.floor((F.col(c) - float(a)) / max(float(b) - float(a), 1e-300) * bins), F.lit(0)), F.lit(bins - 1)).cast("int")
    count = lambda df: {r["c"]: r["count"] for r in df.where(in_box(cols, lo, hi)).groupBy(cell.alias("c")).count().collect()}
    got, all_ = count(sample), count(whole)
    n, total = sum(got.values()), max(1, sum(all_.values()))
    expected = {c: m * n / total for c, m in all_.items()}
    value = sum((got.get(c, 0) - e) ** 2 / e for c, e in expected.items() if e > 0)
    return float(value / max(1, len(expected) - 1)), len(expected)
