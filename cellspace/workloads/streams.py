"""Streaming workloads; each runs a stream over the whole events table and gives its result as a table."""

from __future__ import annotations

from pyspark.sql import functions as F

from cellspace.functions.spaces import EVENT3, LINE3
from cellspace.operators import lod
from cellspace.operators.kdtree import locate_leaves
from cellspace.plans.shared import new_path, staged
from cellspace.sources.layout import table
from cellspace.streaming import views as sv
from cellspace.workloads.base import grid, kd, query

_DAY = "CAST(CAST(date_trunc('day', ts) AS DATE) AS VARCHAR)"


@query("st_tumbling", f"SELECT {_DAY} AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def tumbling(spark, d):
    out = sv.run_to_table(sv.tumbling_counts(sv.events_stream(spark, d)), "complete")
    return out.select(F.to_date("start").cast("string").alias("start"), "event_type", "n", F.round("total", 4).alias("total"))


@query("st_sliding", "SELECT CAST(CAST(day AS DATE) - CAST(k AS INTEGER) AS VARCHAR) AS start, count(*) AS n FROM (SELECT date_trunc('day', ts) AS day FROM events), range(2) AS r(k) GROUP BY ALL")
def sliding(spark, d):
    out = sv.run_to_table(sv.sliding_counts(sv.events_stream(spark, d)), "complete")
    return out.select(F.to_date("start").cast("string").alias("start"), "n")


def _far(e, years=(2100, 2101)):
    """Rows far in the future, one after the other, that push the watermark past everything else; late rows are judged
    by the watermark of the batch before."""
    nothing = [F.lit(None).cast(f.dataType).alias(f.name) if f.name != "ts" else None for f in e.schema]
    return [e.limit(1).select(*[F.lit(f"{year}-01-01").cast("timestamp").alias("ts") if c is None else c for c in nothing]) for year in years]


@query("st_session", "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS no FROM g) SELECT user_id, epoch(min(ts)) AS start, count(*) AS n FROM s GROUP BY user_id, no")
def session(spark, d):
    """Sessions of each user as a stream: a session is given out when the watermark has passed its end, the last ones by
    an event far in the future."""
    e = table(spark, d, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts"))
    stream = sv.stream_in_turn(spark, [e, *_far(e)], "sessions")
    out = sv.run_to_table(sv.session_counts(stream.withWatermark("ts", "1 hour")), "append")
    return out.where("user_id is not null").select("user_id", F.col("start").cast("double").alias("start"), "n")


_LATE = "event_id % 50 = 7"  # these come again in a second file, after the watermark has passed them


@query("st_watermark_late", f"SELECT {_DAY} AS start, count(*) FILTER (NOT ({_LATE})) AS n FROM events GROUP BY ALL HAVING count(*) FILTER (NOT ({_LATE})) > 0")
def watermark_late(spark, d):
    """Events that come after the watermark has passed their window are left out of it, and only those."""
    e = table(spark, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    stream = sv.stream_in_turn(spark, [e.where(f"NOT ({_LATE})"), *_far(e), e.where(_LATE), *_far(e, (2102, 2103))], "late")
    per = stream.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day")).agg(F.count("event_id").alias("n"))
    out = sv.run_to_table(per.select(F.col("window.start").alias("start"), "n"), "append")
    return out.where("n > 0").select(F.to_date("start").cast("string").alias("start"), "n")


@query("st_assign_frozen", f"SELECT CAST(count(*) AS BIGINT) AS n FROM ({EVENT3.sql()})")
def assign_frozen(spark, d):
    """Streamed rows get the leaf of an index that is fixed."""
    _, tree = kd(spark, d, EVENT3)
    stream = sv.space_stream(spark, d, EVENT3)
    found = sv.run_to_table(locate_leaves(stream, tree, EVENT3.cols, ["key"]))
    return found.where(F.col("leaf").between(0, tree.leaves - 1)).agg(F.count("*").alias("n"))


@query("st_foreach_lod")
def foreach_lod(spark, d):
    """Each micro-batch of views is answered with the boxes of the right size in view, appended to a table."""
    _, tree = kd(spark, d, LINE3)
    g = grid(spark, d, LINE3, 64)
    e = sv.events_stream(spark, d)
    out = new_path(spark, "lod")

    def answer(batch, number):
        views = batch.orderBy("event_id").select("event_id", "value").toArrow()  # one batch of views, newest per user
        found = []
        for i, v in zip(views["event_id"].to_pylist(), views["value"].to_pylist(), strict=True):
            zoom = min(v / 100, 0.9) / 2
            lo = tuple(a + (b - a) * zoom for a, b in zip(g.lo, g.hi, strict=True))
            hi = tuple(b - (b - a) * zoom for a, b in zip(g.lo, g.hi, strict=True))
            h, nodes = lod.visible_boxes(tree, lod.View(lo, hi, 100))
            found.append((i, h, len(nodes), number))
        spark.createDataFrame(found, "event_id long, height int, boxes int, batch long").write.mode("append").parquet(out)

    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    newest = sv.newest_views(e)
    q = newest.writeStream.outputMode("update").foreachBatch(answer).option("checkpointLocation", new_path(spark, "lod-state")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(out)


@query("st_dedup", "SELECT count(*) AS n FROM events")
def dedup(spark, d):
    """Every event comes twice; each is kept once."""
    e = sv.events_stream(spark, d).withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1)))).drop("copy")
    out = sv.run_to_table(sv.without_repeats(e, "3650 days").select("event_id"))
    return out.agg(F.count("*").alias("n"))


@query("st_latest_view", "SELECT user_id, max(event_id) AS event_id, count(*) AS seen FROM events GROUP BY user_id")
def latest_view(spark, d):
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    out = sv.run_to_table(sv.newest_views(sv.events_stream(spark, d)), "update")
    return out.select("user_id", "event_id", "seen")


@query("st_static_join", "SELECT n_name, count(*) AS n FROM events JOIN nation ON user_id % 25 = n_nationkey GROUP BY n_name")
def static_join(spark, d):
    e = sv.events_stream(spark, d).withColumn("n_nationkey", (F.col("user_id") % 25).cast("int"))
    j = sv.static_join(e.select("n_nationkey"), table(spark, d, "nation").select("n_nationkey", "n_name"), "n_nationkey")
    return sv.run_to_table(j.groupBy("n_name").agg(F.count("*").alias("n")), "complete")


@query("W_camera_stream")
def camera_stream(spark, d):
    """Events as view changes: the newest view of each user becomes a request, answered in micro-batches by the grid,
    whose layers are read until a view has its points; a view of an empty box has none."""
    g = grid(spark, d, LINE3, 64)
    e = sv.events_stream(spark, d)
    zoom = F.least(F.col("value") / 100, F.lit(0.9))
    lo = F.array(*[F.lit(a) + (b - a) * zoom / 2 for a, b in zip(g.lo, g.hi, strict=True)])
    hi = F.array(*[F.lit(b) - (b - a) * zoom / 2 for a, b in zip(g.lo, g.hi, strict=True)])
    views = e.select(F.col("event_id").cast("int").alias("request_id"), "user_id", "ts", lo.alias("lo"), hi.alias("hi"), F.lit(20).alias("wanted"))
    out = new_path(spark, "answers")

    def answer(batch, number):
        newest = batch.groupBy("user_id").agg(F.max_by(F.struct("request_id", "lo", "hi", "wanted"), F.struct("ts", "request_id")).alias("v")).select("v.*")
        from cellspace.operators.grid import sample_boxes

        newest = staged(newest, "requests")
        points = sample_boxes(g, newest, newest.count()).groupBy("request_id").agg(F.count("*").alias("points"))
        every = newest.select("request_id").join(points, "request_id", "left").withColumn("points", F.coalesce("points", F.lit(0).cast("long")))
        every.withColumn("batch", F.lit(number)).write.mode("append").parquet(out)

    q = views.writeStream.foreachBatch(answer).option("checkpointLocation", new_path(spark, "camera")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(out)
