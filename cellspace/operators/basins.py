"""Clusters of cells by climbing density: parents, peaks, agreement with labels, outliers and votes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cellspace.plans.shared import staged


def basin_tree(cells: DataFrame, edges: DataFrame) -> DataFrame:
    """(cell_tag, density, parent_tag): the densest of a cell and its neighbours, ties to the lower tag, so density
    rises along parents and a cell without a denser neighbour is its own parent, a peak."""
    both = edges.select("src", "dst").union(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    dense = cells.select(F.col("cell_tag").alias("dst"), F.col("density").alias("there"))
    near = both.join(dense, "dst").groupBy(F.col("src").alias("cell_tag")).agg(F.max(F.struct(F.col("there"), (-F.col("dst")).alias("minus"))).alias("m"))
    out = cells.join(near, "cell_tag", "left")
    up = F.col("m").isNotNull() & ((F.col("m.there") > F.col("density")) | ((F.col("m.there") == F.col("density")) & (-F.col("m.minus") < F.col("cell_tag"))))
    return out.select("cell_tag", "density", F.when(up, -F.col("m.minus")).otherwise(F.col("cell_tag")).alias("parent_tag"))


def basin_clusters(tree: DataFrame, rounds: int = 40) -> DataFrame:
    """(cell_tag, cluster): the peak above each cell, by doubling pointers; rounds are the logarithm of the depth."""
    now = staged(tree.select("cell_tag", F.col("parent_tag").alias("cluster")), "basin")
    for _ in range(rounds):
        up = now.select(F.col("cell_tag").alias("cluster"), F.col("cluster").alias("peak"))
        new = staged(now.join(up, "cluster").select("cell_tag", F.col("peak").alias("cluster"), (F.col("peak") != F.col("cluster")).alias("moved")), "basin")
        moved = new.where("moved").limit(1).count()
        now = new.select("cell_tag", "cluster")
        if not moved:
            return now
    raise RuntimeError("the forest has a cycle")


def merge_weak_peaks(tree: DataFrame, clusters: DataFrame, edges: DataFrame, prominence: float) -> DataFrame:
    """(cell_tag, cluster): peaks whose density is less than ``prominence`` times that of their best pass join the
    densest basin over it, again and again. Passes are few, so this runs on the driver over peaks only."""
    named = clusters.join(tree.select("cell_tag", "density"), "cell_tag")
    a = named.select(F.col("cell_tag").alias("src"), F.col("cluster").alias("ca"), F.col("density").alias("da"))
    b = named.select(F.col("cell_tag").alias("dst"), F.col("cluster").alias("cb"), F.col("density").alias("db"))
    passes = edges.join(a, "src").join(b, "dst").where("ca != cb").groupBy(F.least("ca", "cb").alias("p"), F.greatest("ca", "cb").alias("q")).agg(F.max(F.least("da", "db")).alias("saddle")).collect()
    peak = {r["cell_tag"]: r["density"] for r in named.where("cell_tag = cluster").collect()}
    to = {p: p for p in peak}

    def top(p):
        while to[p] != p:
            p = to[p]
        return p

    for r in sorted(passes, key=lambda r: (-r["saddle"], r["p"], r["q"])):
        p, q = top(r["p"]), top(r["q"])
        if p == q:
            continue
        low, high = sorted((p, q), key=lambda t: (peak[t], -t))
        if peak[low] < prominence * r["saddle"]:
            to[low] = high
    table = clusters.sparkSession.createDataFrame([(int(p), int(top(p))) for p in peak], "cluster long, merged long")
    return clusters.join(F.broadcast(table), "cluster").select("cell_tag", F.col("merged").alias("cluster"))


def cluster_agreement(rows: DataFrame, label: str) -> DataFrame:
    """(cluster, n, majority_label, majority_n) over rows with a cluster and a label that isn't null."""
    per = rows.where(F.col(label).isNotNull()).groupBy("cluster", F.col(label).alias("majority_label")).agg(F.count("*").alias("majority_n"))
    w = Window.partitionBy("cluster")
    per = per.withColumn("n", F.sum("majority_n").over(w)).withColumn("r", F.row_number().over(w.orderBy(F.desc("majority_n"), "majority_label")))
    return per.where("r = 1").select("cluster", "n", "majority_label", "majority_n")


def agreement_summary(agreement: DataFrame, rows: DataFrame, label: str) -> DataFrame:
    """(clusters, labelled, agreement, majority_baseline)"""
    most = rows.where(F.col(label).isNotNull()).groupBy(label).count().agg(F.max("count").alias("m"), F.sum("count").alias("s"))
    out = agreement.agg(F.count("*").alias("clusters"), F.sum("n").alias("labelled"), F.sum("majority_n").alias("hit"))
    return out.crossJoin(most).select("clusters", "labelled", (F.col("hit") / F.col("labelled")).alias("agreement"), (F.col("m") / F.col("s")).alias("majority_baseline"))


def volume_outliers(rows: DataFrame, cells: DataFrame, share: float) -> DataFrame:
    """Rows of the cells whose volume is above the (1 - share) quantile of cell volumes."""
    cut = cells.agg(F.expr(f"percentile_disc({1 - share}) WITHIN GROUP (ORDER BY volume)")).first()[0]
    return rows.join(cells.where(F.col("volume") > F.lit(cut)).select("cell_tag", "volume"), "cell_tag")


def leaf_outliers(index: DataFrame, cols: list[str], share: float) -> DataFrame:
    """Rows of the kd leaves whose tight box is largest (by the same rule)."""
    volume = F.lit(1.0)
    for c in cols:
        volume = volume * (F.max(c) - F.min(c))
    leaves = index.groupBy("leaf").agg(volume.alias("volume"))
    cut = leaves.agg(F.expr(f"percentile_disc({1 - share}) WITHIN GROUP (ORDER BY volume)")).first()[0]
    return index.join(leaves.where(F.col("volume") > F.lit(cut)), "leaf")


def vote(neighbours: DataFrame, labels: DataFrame) -> DataFrame:
    """(query_key, label) by majority of the neighbours' labels, ties to the lower label."""
    per = neighbours.join(labels, "key").groupBy("query_key", "label").agg(F.count("*").alias("n"))
    w = Window.partitionBy("query_key").orderBy(F.desc("n"), "label")
    return per.withColumn("r", F.row_number().over(w)).where("r = 1").select("query_key", "label")
