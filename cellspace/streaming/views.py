"""Streams of view changes: windows, late and repeated events, newest view of each session, frozen index lookup."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from cellspace.functions.spaces import clean
from cellspace.plans.shared import new_path


def events_stream(spark: SparkSession, sf_dir: str, files: int = 1) -> DataFrame:
    """``events`` as a stream, ts as a timestamp."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    import os

    glob = path if os.path.isdir(path) else None
    if glob:
        stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)
    else:
        stream = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(os.path.dirname(path))
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def stream_in_turn(spark: SparkSession, parts: list[DataFrame], tag: str) -> DataFrame:
    """A stream of tables, one file and one micro-batch each, in their order: what comes late comes late."""
    path = new_path(spark, tag)
    for part in parts:
        part.coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(parts[0].schema).option("maxFilesPerTrigger", 1).parquet(path)


def space_stream(spark: SparkSession, sf_dir: str, space) -> DataFrame:
    """Keys and features of a space over ``events``, as a stream."""
    cols = [f"cast({e} AS double) AS x{k}" for k, e in enumerate(space.features)]
    return clean(events_stream(spark, sf_dir).selectExpr(f"{space.key} AS key", *cols), space.cols)


def run_to_table(stream: DataFrame, mode: str = "append", tag: str = "stream") -> DataFrame:
    """Runs a stream over what there is and gives its result as a table.

    Append mode writes files with a checkpoint in the shared folder, so a restart goes on where it stopped. Update and
    complete modes keep the last batch's rows the same way.
    """
    spark = stream.sparkSession
    out, check = new_path(spark, tag), new_path(spark, f"{tag}-check")
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", check).outputMode("append").trigger(availableNow=True).start()
        q.awaitTermination()
    else:

        def keep(batch: DataFrame, _: int) -> None:
            batch.write.mode("overwrite").parquet(out)

        q = stream.writeStream.foreachBatch(keep).option("checkpointLocation", check).outputMode(mode).trigger(availableNow=True).start()
        q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def tumbling_counts(events: DataFrame, width: str = "1 day") -> DataFrame:
    w = F.window("ts", width)
    return events.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", "total")


def sliding_counts(events: DataFrame, width: str = "2 days", step: str = "1 day") -> DataFrame:
    return events.groupBy(F.window("ts", width, step).alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def session_counts(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    return events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def without_repeats(events: DataFrame, delay: str = "1 day") -> DataFrame:
    """Repeated events within the watermark go."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


class NewestView(StatefulProcessor):
    """The newest view of a session and how many it has had; older ones that come late don't replace it."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.newest = handle.getValueState("newest", "ts timestamp, event_id long, value double, seen long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        best = self.newest.get() if self.newest.exists() else None
        best = tuple(best) if best is not None else None
        seen = best[3] if best else 0
        for pdf in rows:
            seen += len(pdf)
            top = pdf.sort_values(["ts", "event_id"]).iloc[-1]
            mine = (top.ts.to_pydatetime(), int(top.event_id), float(top.value))
            if best is None or mine[:2] > tuple(best[:2]):
                best = (*mine, seen)
        best = (*best[:3], seen)
        self.newest.update(best)
        yield pd.DataFrame({"user_id": [key[0]], "ts": [best[0]], "event_id": [best[1]], "value": [best[2]], "seen": [seen]})

    def close(self) -> None:
        pass


def newest_views(events: DataFrame) -> DataFrame:
    return events.select("user_id", "ts", "event_id", "value").groupBy("user_id").transformWithStateInPandas(NewestView(), "user_id long, ts timestamp, event_id long, value double, seen long", "Update", "None")


def serve_views(views: DataFrame, grid, wanted: int, answer_path: str):
    """foreachBatch: every micro-batch of views (request_id, lo, hi, wanted) is answered by one batched sample."""
    from cellspace.operators.grid import sample_boxes

    def answer(batch: DataFrame, number: int) -> None:
        sample_boxes(grid, batch, wanted).select("request_id", "key", "layer", "rand_rank").withColumn("batch", F.lit(number)).write.mode("append").parquet(answer_path)

    return views.writeStream.foreachBatch(answer).option("checkpointLocation", new_path(views.sparkSession, f"serve-{uuid.uuid4().hex[:6]}")).trigger(availableNow=True).start()


def static_join(stream: DataFrame, table: DataFrame, on: str) -> DataFrame:
    return stream.join(table, on)
