"""Shared folder, written tables, size-checked broadcasts and distributed row numbers."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: A side of a join is broadcast only if its counted rows, at their width, are within this many bytes.
BROADCAST_BYTES = 64_000_000
#: A window over one group runs in one task; larger tables are numbered by a range sort instead.
WINDOW_ROWS = 4_000_000

_OWN: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session; an own folder only where it is unset and the master is local."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    master, app = spark.sparkContext.master, spark.sparkContext.applicationId
    if not (master == "local" or master.startswith("local[")):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    if app not in _OWN:
        _OWN[app] = "file://" + tempfile.mkdtemp(prefix="cellspace-")
    return _OWN[app]


def new_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"


def staged(df: DataFrame, tag: str) -> DataFrame:
    """``df`` written to the shared folder and read back: its lineage ends there and survives lost executors."""
    path = new_path(df.sparkSession, tag)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def spread(df: DataFrame) -> DataFrame:
    """``df``, a plain scan, in as many partitions as there are cores at least: a small table in one file would give one
    task to every kernel after it."""
    want = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(want) if df.rdd.getNumPartitions() < want else df


def row_width(df: DataFrame) -> int:
    """Bytes of a row, about: 8 a number, 40 a string, 120 anything nested."""
    return sum(8 if kind in ("bigint", "int", "double", "float", "boolean", "date", "timestamp", "timestamp_ntz") else 40 if kind == "string" else 120 for _, kind in df.dtypes)


def maybe_broadcast(df: DataFrame, rows: int) -> DataFrame:
    return F.broadcast(df) if rows * row_width(df) <= BROADCAST_BYTES else df


def row_numbers(df: DataFrame, order: list, name: str, rows: int | None = None) -> DataFrame:
    """``name``: 1, 2, ... in the total order ``order``, without a window over the whole table.

    A range sort is written once; the driver gets a row count for each partition and their prefix sums go back as
    offsets. Small tables (``rows`` within WINDOW_ROWS) take one window.
    """
    if rows is not None and rows <= WINDOW_ROWS:
        return df.withColumn(name, F.row_number().over(Window.orderBy(*order)))
    sort = df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("__at", F.monotonically_increasing_id())
    sort = staged(sort, "sorted")
    part = F.shiftrightunsigned("__at", 33)
    counts = sorted((r["p"], r["n"]) for r in sort.groupBy(part.alias("p")).agg(F.count("*").alias("n")).collect())
    offsets, total = [], 0
    for p, n in counts:
        offsets.append((p, total))
        total += n
    table = df.sparkSession.createDataFrame(offsets, "__part long, __offset long")
    out = sort.withColumn("__part", part).join(F.broadcast(table), "__part")
    inside = F.col("__at").bitwiseAND(F.lit((1 << 33) - 1))
    return out.withColumn(name, F.col("__offset") + inside + 1).drop("__part", "__offset", "__at")


def hash_60(*text: Column | str) -> Column:
    """60 bits of the MD5 of the joined text, the same in Spark and other SQL engines."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *text)), 1, 15), 16, 10).cast("long")
