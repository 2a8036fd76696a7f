"""Clustered layouts: files in key order with small row groups, read back with pruning; flat-file export."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellspace.plans.shared import new_path

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name not in TABLES:
        raise KeyError(name)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def write_clustered(df: DataFrame, by: list[str], path: str | None = None, files: int | None = None, row_group_bytes: int = 64 << 20) -> str:
    """Range-partitioned, sorted Parquet: one shuffle. Row-group statistics then prune ranges of ``by``."""
    path = new_path(df.sparkSession, "layout") if path is None else path
    out = df.repartitionByRange(*([files] if files else []), *by).sortWithinPartitions(*by)
    out.write.option("parquet.block.size", str(row_group_bytes)).parquet(path)
    return path


def read_ranges(spark: SparkSession, path: str, column: str, ranges: list[tuple[int, int]]) -> DataFrame:
    """Rows whose ``column`` lies in one of the ranges; the condition is pushed to the files."""
    cond = F.lit(False)
    for a, b in ranges:
        cond = cond | F.col(column).between(a, b)
    return spark.read.parquet(path).where(cond)


def export_flat(df: DataFrame, kind: str = "csv", path: str | None = None) -> str:
    """Baseline: the whole table as text files."""
    path = new_path(df.sparkSession, "flat") if path is None else path
    (df.write.option("header", True).csv(path) if kind == "csv" else df.write.json(path))
    return path


def rows_scanned(df: DataFrame) -> int:
    """Rows that the executed scans of ``df`` put out: runs it once and reads the scans' metrics."""
    df.foreach(lambda _: None) if False else df._jdf.queryExecution().toRdd().count()

    def walk(plan) -> int:
        name, total = plan.nodeName(), 0
        if name.startswith("Scan parquet"):
            total += plan.metrics().get("numOutputRows").get().value()
        if name == "AdaptiveSparkPlan":
            return walk(plan.executedPlan())
        kids = plan.children()
        for k in range(kids.size()):
            total += walk(kids.apply(k))
        if "QueryStage" in name:
            total += walk(plan.plan())
        return total

    return walk(df._jdf.queryExecution().executedPlan())


def scene_json(df: DataFrame) -> DataFrame:
    """One JSON text for each row."""
    return df.select(F.to_json(F.struct(*df.columns)).alias("geometry"))


def manifest(path: str, **facts) -> str:
    return json.dumps({"path": path, **facts}, sort_keys=True)
