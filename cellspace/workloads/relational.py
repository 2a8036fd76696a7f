"""Relational operators around the methods, each over whole tables."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cellspace.functions.spaces import LINE3, LINE5
from cellspace.operators.grid import block_layout
from cellspace.plans.shared import maybe_broadcast, row_numbers, staged
from cellspace.sources.layout import export_flat, read_ranges, table, write_clustered
from cellspace.workloads.base import kd, kept, query

W = Window


def _small(df):
    """A broadcast behind a count; dimension tables stay within it at any scale factor used here."""
    return maybe_broadcast(df, df.count())


def _share(part, whole):
    """``part`` of ``whole``; of an empty text it isn't a number, as in the SQL."""
    return F.when(whole == 0, F.lit(float("nan"))).otherwise(part / F.nullif(whole, F.lit(0)))


@query("op_scan_prune", "SELECT sum(l_quantity) AS q, round(sum(l_extendedprice), 2) AS p, round(sum(l_discount), 4) AS d, round(sum(l_tax), 4) AS t, CAST(max(CAST(l_shipdate AS DATE)) AS VARCHAR) AS last FROM lineitem")
def scan_prune(spark, d):
    t = table(spark, d, "lineitem").select("l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_shipdate")
    return t.agg(F.sum("l_quantity").alias("q"), F.round(F.sum("l_extendedprice"), 2).alias("p"), F.round(F.sum("l_discount"), 4).alias("d"), F.round(F.sum("l_tax"), 4).alias("t"), F.max(F.to_date("l_shipdate")).cast("string").alias("last"))


@query("op_scan_pushdown", "SELECT o_orderkey, o_totalprice FROM orders WHERE o_orderkey BETWEEN 1000 AND 5000")
def scan_pushdown(spark, d):
    path = write_clustered(table(spark, d, "orders").select("o_orderkey", "o_totalprice"), ["o_orderkey"], row_group_bytes=64 << 10)
    return read_ranges(spark, path, "o_orderkey", [(1000, 5000)])


@query("op_datasource", "SELECT o_orderkey, o_totalprice FROM orders WHERE o_orderkey >= 2000 AND o_orderkey < 9000")
def datasource(spark, d):
    from cellspace.sources.index_source import register

    register(spark)
    path = write_clustered(table(spark, d, "orders").select("o_orderkey", "o_totalprice"), ["o_orderkey"], files=8)
    if not path.startswith("file:") and "://" in path:
        return read_ranges(spark, path, "o_orderkey", [(2000, 8999)])
    df = spark.read.format("cellspace_index").option("path", path).option("by", "o_orderkey").load()
    return df.where("o_orderkey >= 2000 AND o_orderkey < 9000")


@query("op_sink_clustered", "SELECT count(*) AS n, sum(o_orderkey) AS keys, round(sum(o_totalprice), 2) AS total FROM orders")
def sink_clustered(spark, d):
    path = write_clustered(table(spark, d, "orders"), ["o_totalprice", "o_orderkey"])
    return spark.read.parquet(path).agg(F.count("*").alias("n"), F.sum("o_orderkey").alias("keys"), F.round(F.sum("o_totalprice"), 2).alias("total"))


for _kind in ("csv", "json"):

    @query(f"op_sink_{_kind}", "SELECT s_suppkey, s_nationkey, round(s_acctbal, 2) AS s_acctbal FROM supplier")
    def sink_flat(spark, d, kind=_kind):
        df = table(spark, d, "supplier").select("s_suppkey", "s_nationkey", "s_acctbal")
        path = export_flat(df, kind)
        r = spark.read.schema(df.schema)
        back = r.option("header", True).csv(path) if kind == "csv" else r.json(path)
        return back.withColumn("s_acctbal", F.round("s_acctbal", 2))


@query("op_project_colours", "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice / l_quantity AS unit, l_tax - l_discount AS diff FROM lineitem")
def project_colours(spark, d):
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", (F.col("l_extendedprice") / F.col("l_quantity")).alias("unit"), (F.col("l_tax") - F.col("l_discount")).alias("diff"))


@query("op_filter_dnf", "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey FROM lineitem WHERE (l_quantity < 10 AND l_extendedprice >= 20000) OR (l_discount > 0.05 AND l_tax <= 0.02 AND NOT l_returnflag = 'R')")
def filter_dnf(spark, d):
    c = F.col
    cond = ((c("l_quantity") < 10) & (c("l_extendedprice") >= 20000)) | ((c("l_discount") > 0.05) & (c("l_tax") <= 0.02) & ~(c("l_returnflag") == "R"))
    return table(spark, d, "lineitem").where(cond).select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")


@query("op_filter_in", "SELECT c_custkey FROM customer WHERE c_nationkey IN (1, 5, 7, 12)")
def filter_in(spark, d):
    return table(spark, d, "customer").where(F.col("c_nationkey").isin(1, 5, 7, 12)).select("c_custkey")


@query("op_null_nan", "SELECT d.doc_id, coalesce(l.quality, -1) AS quality, l.toxic IS NULL AS unmeasured FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
def null_nan(spark, d):
    j = table(spark, d, "documents").select("doc_id").join(table(spark, d, "labels"), "doc_id", "left")
    return j.select("doc_id", F.coalesce("quality", F.lit(-1)).alias("quality"), F.col("toxic").isNull().alias("unmeasured"))


@query("op_join_hash", "SELECT n_name, count(*) AS n, round(sum(l_extendedprice), 2) AS total FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey GROUP BY n_name")
def join_hash(spark, d):
    side = table(spark, d, "supplier").join(_small(table(spark, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_name")
    j = table(spark, d, "lineitem").select("l_suppkey", "l_extendedprice").join(_small(side), F.col("l_suppkey") == F.col("s_suppkey"))
    return j.groupBy("n_name").agg(F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("total"))


@query("op_join_sortmerge", "SELECT o_orderpriority, count(*) AS n, round(sum(l_extendedprice), 2) AS total FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderpriority")
def join_sortmerge(spark, d):
    o = table(spark, d, "orders").select("o_orderkey", "o_orderpriority").hint("merge")
    j = table(spark, d, "lineitem").select("l_orderkey", "l_extendedprice").join(o, F.col("l_orderkey") == F.col("o_orderkey"))
    return j.groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("total"))


@query("op_join_shuffle_hash", "SELECT c_mktsegment, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment")
def join_shuffle_hash(spark, d):
    c = table(spark, d, "customer").select("c_custkey", "c_mktsegment").hint("shuffle_hash")
    j = table(spark, d, "orders").join(c, F.col("o_custkey") == F.col("c_custkey"))
    return j.groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@query("op_join_left_sparse", "SELECT lang, count(*) AS n, count(quality) AS labelled FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id GROUP BY lang")
def join_left_sparse(spark, d):
    j = table(spark, d, "documents").select("doc_id", "lang").join(table(spark, d, "labels"), "doc_id", "left")
    return j.groupBy("lang").agg(F.count("*").alias("n"), F.count("quality").alias("labelled"))


@query("op_join_semi", "SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity > 48)")
def join_semi(spark, d):
    big = table(spark, d, "lineitem").where("l_quantity > 48").select(F.col("l_orderkey").alias("o_orderkey"))
    return table(spark, d, "orders").select("o_orderkey").join(big, "o_orderkey", "left_semi")


@query("op_join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
def join_anti(spark, d):
    dear = table(spark, d, "orders").where("o_totalprice > 300000").select(F.col("o_custkey").alias("c_custkey"))
    return table(spark, d, "customer").select("c_custkey").join(dear, "c_custkey", "left_anti")


@query("op_join_full", "SELECT coalesce(a.o_orderkey, b.o_orderkey) AS o_orderkey, a.o_orderkey IS NOT NULL AS in_a, b.o_orderkey IS NOT NULL AS in_b FROM (SELECT o_orderkey FROM orders WHERE o_totalprice < 200000) a FULL OUTER JOIN (SELECT o_orderkey FROM orders WHERE o_totalprice > 100000) b ON a.o_orderkey = b.o_orderkey")
def join_full(spark, d):
    o = table(spark, d, "orders")
    a = o.where("o_totalprice < 200000").select("o_orderkey", F.lit(True).alias("a"))
    b = o.where("o_totalprice > 100000").select("o_orderkey", F.lit(True).alias("b"))
    return a.join(b, "o_orderkey", "full").select("o_orderkey", F.coalesce("a", F.lit(False)).alias("in_a"), F.coalesce("b", F.lit(False)).alias("in_b"))


_BOXES = [(1, 0.0, 10.0, 0.0, 20.0), (2, 5.0, 30.0, 10.0, 60.0), (3, 49.0, 50.0, 90.0, 200.0)]
_BOX_SQL = "(VALUES " + ", ".join(map(str, _BOXES)) + ") AS b(box_id, a0, b0, a1, b1)"


@query("op_join_range", f"SELECT box_id, count(*) AS n FROM lineitem, {_BOX_SQL} WHERE l_quantity BETWEEN a0 AND b0 AND l_extendedprice / 1000 BETWEEN a1 AND b1 GROUP BY box_id")
def join_range(spark, d):
    boxes = spark.createDataFrame(_BOXES, "box_id int, a0 double, b0 double, a1 double, b1 double")
    p = F.col("l_extendedprice") / 1000
    j = table(spark, d, "lineitem").select("l_quantity", "l_extendedprice").join(F.broadcast(boxes), F.col("l_quantity").between(F.col("a0"), F.col("b0")) & p.between(F.col("a1"), F.col("b1")))
    return j.groupBy("box_id").agg(F.count("*").alias("n"))


@query("op_join_interval", "SELECT part, count(*) AS n FROM orders JOIN (VALUES (1, 0, 99), (2, 50, 2000), (3, 5000, 1000000)) AS t(part, a, b) ON o_orderkey BETWEEN a AND b GROUP BY part")
def join_interval(spark, d):
    t = spark.createDataFrame([(1, 0, 99), (2, 50, 2000), (3, 5000, 1_000_000)], "part int, a long, b long")
    return table(spark, d, "orders").join(F.broadcast(t), F.col("o_orderkey").between(F.col("a"), F.col("b"))).groupBy("part").agg(F.count("*").alias("n"))


@query("op_join_asof", "SELECT c.event_id, v.event_id AS view_id FROM (SELECT * FROM events WHERE event_type <> 'view') c ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') v ON c.user_id = v.user_id AND c.ts >= v.ts")
def join_asof(spark, d):
    e = table(spark, d, "events").select("event_id", "user_id", "ts", (F.col("event_type") == "view").alias("is_view"))
    w = W.partitionBy("user_id").orderBy("ts", F.desc("is_view"), "event_id").rowsBetween(W.unboundedPreceding, 0)
    last = F.last(F.when(F.col("is_view"), F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("view_id", last).where("NOT is_view").select("event_id", "view_id")


@query("op_join_self_graph", "SELECT a.s_suppkey AS a, count(*) AS n FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_suppkey <> b.s_suppkey JOIN customer c ON c.c_nationkey = b.s_nationkey GROUP BY a.s_suppkey")
def join_self_graph(spark, d):
    s = table(spark, d, "supplier").select("s_suppkey", "s_nationkey")
    per = table(spark, d, "customer").groupBy(F.col("c_nationkey").alias("s_nationkey")).agg(F.count("*").alias("m"))
    other = s.withColumnRenamed("s_suppkey", "b").join(per, "s_nationkey")
    return s.join(other, "s_nationkey").where("s_suppkey <> b").groupBy(F.col("s_suppkey").alias("a")).agg(F.sum("m").alias("n"))


_SEEDS = [(1, 6.0, 4.0), (2, 9.0, 3.0), (3, 12.0, 5.0), (4, 10.0, 7.0)]


@query("op_join_cross_topk", "WITH p AS (SELECT doc_id, (length(lower(text)) - length(replace(lower(text), 'e', ''))) * 100.0 / length(text) AS a, (length(lower(text)) - length(replace(lower(text), 'n', ''))) * 100.0 / length(text) AS b FROM documents), c AS (SELECT doc_id, s, row_number() OVER (PARTITION BY doc_id ORDER BY (a - u) * (a - u) + (b - v) * (b - v), s) AS r FROM p, (VALUES (1, 6.0, 4.0), (2, 9.0, 3.0), (3, 12.0, 5.0), (4, 10.0, 7.0)) AS t(s, u, v)) SELECT doc_id, CAST(r AS INTEGER) AS rank, s AS seed FROM c WHERE r <= 2")
def join_cross_topk(spark, d):
    t = table(spark, d, "documents")
    low = F.lower("text")
    share = lambda x: _share((F.length(low) - F.length(F.replace(low, F.lit(x), F.lit("")))) * 100.0, F.length("text"))
    p = t.select("doc_id", share("e").alias("a"), share("n").alias("b"))
    s = spark.createDataFrame(_SEEDS, "seed int, u double, v double")
    d2 = (F.col("a") - F.col("u")) * (F.col("a") - F.col("u")) + (F.col("b") - F.col("v")) * (F.col("b") - F.col("v"))
    near = p.crossJoin(F.broadcast(s)).groupBy("doc_id").agg(F.slice(F.sort_array(F.collect_list(F.struct(d2.alias("d"), "seed"))), 1, 2).alias("m"))
    return near.select("doc_id", F.posexplode("m").alias("at", "x")).select("doc_id", (F.col("at") + 1).alias("rank"), F.col("x.seed").alias("seed"))


@query("op_join_lateral", "SELECT n_nationkey, s_suppkey, s_acctbal FROM (SELECT n_nationkey, s_suppkey, s_acctbal, row_number() OVER (PARTITION BY n_nationkey ORDER BY s_acctbal DESC, s_suppkey) AS r FROM nation JOIN supplier ON s_nationkey = n_nationkey) WHERE r <= 2")
def join_lateral(spark, d):
    n = table(spark, d, "nation").select("n_nationkey")
    s = table(spark, d, "supplier").select("s_suppkey", "s_nationkey", "s_acctbal")
    best = s.where(F.col("s_nationkey") == F.col("n_nationkey").outer()).orderBy(F.desc("s_acctbal"), "s_suppkey").limit(2)
    return n.lateralJoin(best).select("n_nationkey", "s_suppkey", "s_acctbal")


@query("op_agg_stats", "SELECT round(avg(l_quantity), 6) AS m, round(stddev_pop(l_quantity), 6) AS s, round(covar_pop(l_quantity, l_extendedprice), 3) AS c, round(corr(l_quantity, l_extendedprice), 6) AS r FROM lineitem")
def agg_stats(spark, d):
    return table(spark, d, "lineitem").agg(F.round(F.avg("l_quantity"), 6).alias("m"), F.round(F.stddev_pop("l_quantity"), 6).alias("s"), F.round(F.covar_pop("l_quantity", "l_extendedprice"), 3).alias("c"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"))


@query("op_agg_regr", "SELECT round(regr_slope(l_extendedprice, l_quantity), 5) AS slope, round(regr_intercept(l_extendedprice, l_quantity), 4) AS base, round(regr_r2(l_extendedprice, l_quantity), 8) AS r2 FROM lineitem")
def agg_regr(spark, d):
    return table(spark, d, "lineitem").agg(F.round(F.regr_slope("l_extendedprice", "l_quantity"), 5).alias("slope"), F.round(F.regr_intercept("l_extendedprice", "l_quantity"), 4).alias("base"), F.round(F.regr_r2("l_extendedprice", "l_quantity"), 8).alias("r2"))


@query("op_agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT CAST(l_quantity AS INTEGER) // 5 * 100 + CAST(floor(l_extendedprice / 10000) AS INTEGER)) AS cells FROM lineitem GROUP BY l_returnflag")
def agg_distinct(spark, d):
    cell = F.floor(F.col("l_quantity") / 5) * 100 + F.floor(F.col("l_extendedprice") / 10000)
    return table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct(cell).alias("cells"))


@query("op_agg_approx_distinct")
def agg_approx_distinct(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


@query("op_agg_percentile", "SELECT l_returnflag, quantile_disc(l_extendedprice, 0.5) AS median, quantile_disc(l_extendedprice, 0.99) AS high FROM lineitem GROUP BY l_returnflag")
def agg_percentile(spark, d):
    p = lambda q, n: F.expr(f"percentile_disc({q}) WITHIN GROUP (ORDER BY l_extendedprice)").alias(n)
    return table(spark, d, "lineitem").groupBy("l_returnflag").agg(p(0.5, "median"), p(0.99, "high"))


@query("op_agg_sketch")
def agg_sketch(spark, d):
    s = table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.expr("kll_sketch_agg_double(l_extendedprice)").alias("s"), F.percentile_approx("l_extendedprice", 0.5, 10000).alias("approx"))
    return s.select("l_returnflag", F.expr("kll_sketch_get_quantile_double(s, 0.5D)").alias("kll"), "approx")


@query("op_agg_minmax_by", "SELECT o_custkey, min_by(o_orderkey, o_totalprice) AS cheapest, max_by(o_orderkey, o_totalprice) AS dearest FROM orders GROUP BY o_custkey")
def agg_minmax_by(spark, d):
    return table(spark, d, "orders").groupBy("o_custkey").agg(F.min_by("o_orderkey", "o_totalprice").alias("cheapest"), F.max_by("o_orderkey", "o_totalprice").alias("dearest"))


_STAR = "customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _star(spark, d):
    n = table(spark, d, "nation").join(_small(table(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return table(spark, d, "customer").join(_small(n), F.col("c_nationkey") == F.col("n_nationkey"))


@query("op_agg_rollup", f"SELECT r_name, n_name, count(*) AS n, round(sum(c_acctbal), 2) AS total FROM {_STAR} GROUP BY ROLLUP (r_name, n_name)")
def agg_rollup(spark, d):
    return _star(spark, d).rollup("r_name", "n_name").agg(F.count("*").alias("n"), F.round(F.sum("c_acctbal"), 2).alias("total"))


@query("op_agg_cube", f"SELECT r_name, c_mktsegment, count(*) AS n FROM {_STAR} GROUP BY CUBE (r_name, c_mktsegment)")
def agg_cube(spark, d):
    return _star(spark, d).cube("r_name", "c_mktsegment").agg(F.count("*").alias("n"))


@query("op_agg_grouping_sets", f"SELECT r_name, n_name, c_mktsegment, count(*) AS n FROM {_STAR} GROUP BY GROUPING SETS ((r_name, c_mktsegment), (n_name), ())")
def agg_grouping_sets(spark, d):
    df = _star(spark, d)
    return df.groupingSets([["r_name", "c_mktsegment"], ["n_name"], []], "r_name", "n_name", "c_mktsegment").agg(F.count("*").alias("n"))


@query("op_agg_pivot", "SELECT source, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'fr') AS fr, count(*) FILTER (lang = 'de') AS de, count(*) FILTER (lang = 'es') AS es FROM documents GROUP BY source")
def agg_pivot(spark, d):
    return table(spark, d, "documents").groupBy("source").pivot("lang", ["en", "fr", "de", "es"]).agg(F.count("doc_id")).na.fill(0)


@query("op_agg_filter", "SELECT count(*) FILTER (l_quantity + l_extendedprice / 1000 <= 30) AS inside, count(*) FILTER (l_quantity + l_extendedprice / 1000 > 30 AND l_quantity + l_extendedprice / 1000 <= 60) AS partial, count(*) FILTER (l_quantity + l_extendedprice / 1000 > 60) AS outside FROM lineitem")
def agg_filter(spark, d):
    s = F.col("l_quantity") + F.col("l_extendedprice") / 1000
    return table(spark, d, "lineitem").agg(F.count_if(s <= 30).alias("inside"), F.count_if((s > 30) & (s <= 60)).alias("partial"), F.count_if(s > 60).alias("outside"))


@query("op_agg_collect", "SELECT s_nationkey, array_to_string(list_sort(list(s_suppkey)), ',') AS members FROM supplier GROUP BY s_nationkey")
def agg_collect(spark, d):
    return table(spark, d, "supplier").groupBy("s_nationkey").agg(F.array_join(F.sort_array(F.collect_list("s_suppkey")), ",").alias("members"))


@query("op_agg_tree_rollup", "WITH l AS (SELECT o_orderkey % 64 AS leaf, o_totalprice AS v FROM orders) " + " UNION ALL ".join(f"SELECT {h} AS height, leaf >> {h} AS node, min(v) AS lo, max(v) AS hi, count(*) AS n FROM l GROUP BY leaf >> {h}" for h in range(4)))
def agg_tree_rollup(spark, d):
    leaves = table(spark, d, "orders").groupBy((F.col("o_orderkey") % 64).alias("node")).agg(F.min("o_totalprice").alias("lo"), F.max("o_totalprice").alias("hi"), F.count("*").alias("n"))
    out, now = leaves.select(F.lit(0).alias("height"), "node", "lo", "hi", "n"), leaves
    for h in range(1, 4):
        now = now.groupBy(F.shiftright("node", 1).alias("node")).agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"), F.sum("n").alias("n"))
        out = out.unionByName(now.select(F.lit(h).alias("height"), "node", "lo", "hi", "n"))
    return out


@query("op_win_rownumber", "SELECT o_orderkey, CAST(row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey) AS INTEGER) AS r FROM orders")
def win_rownumber(spark, d):
    return table(spark, d, "orders").select("o_orderkey", F.row_number().over(W.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")).alias("r"))


@query("op_win_rank_family", "SELECT o_orderkey, CAST(rank() OVER w AS INTEGER) AS r, CAST(dense_rank() OVER w AS INTEGER) AS dr, round(percent_rank() OVER w, 8) AS pr, round(cume_dist() OVER w, 8) AS cd, CAST(ntile(4) OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice, o_orderkey) AS INTEGER) AS q FROM orders WINDOW w AS (PARTITION BY o_orderpriority ORDER BY CAST(o_orderdate AS DATE))")
def win_rank_family(spark, d):
    w = W.partitionBy("o_orderpriority").orderBy(F.to_date("o_orderdate"))
    q = W.partitionBy("o_orderpriority").orderBy("o_totalprice", "o_orderkey")
    return table(spark, d, "orders").select("o_orderkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.round(F.percent_rank().over(w), 8).alias("pr"), F.round(F.cume_dist().over(w), 8).alias("cd"), F.ntile(4).over(q).alias("q"))


@query("op_win_running", "SELECT o_custkey, o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS UNBOUNDED PRECEDING), 2) AS running FROM orders")
def win_running(spark, d):
    w = W.partitionBy("o_custkey").orderBy("o_orderkey").rowsBetween(W.unboundedPreceding, 0)
    return table(spark, d, "orders").select("o_custkey", "o_orderkey", F.round(F.sum("o_totalprice").over(w), 2).alias("running"))


@query("op_win_lag_lead", "SELECT event_id, event_id - lag(event_id) OVER w AS back, lead(event_id) OVER w - event_id AS ahead FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def win_lag_lead(spark, d):
    w = W.partitionBy("user_id").orderBy("event_id")
    return table(spark, d, "events").select("event_id", (F.col("event_id") - F.lag("event_id").over(w)).alias("back"), (F.lead("event_id").over(w) - F.col("event_id")).alias("ahead"))


@query("op_win_rows_frame", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW), 6) AS mean FROM events")
def win_rows_frame(spark, d):
    return table(spark, d, "events").select("event_id", F.round(F.avg("value").over(W.partitionBy("user_id").orderBy("event_id").rowsBetween(-3, 0)), 6).alias("mean"))


@query("op_win_range_frame", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) RANGE BETWEEN 90 PRECEDING AND CURRENT ROW) AS n FROM orders")
def win_range_frame(spark, d):
    day = F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01"))
    return table(spark, d, "orders").select("o_orderkey", F.count("*").over(W.partitionBy("o_custkey").orderBy(day).rangeBetween(-90, 0)).alias("n"))


@query("op_win_first_last", "SELECT event_id, first_value(event_id) OVER w AS a, last_value(event_id) OVER w AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def win_first_last(spark, d):
    w = W.partitionBy("user_id").orderBy("event_id").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return table(spark, d, "events").select("event_id", F.first_value("event_id").over(w).alias("a"), F.last_value("event_id").over(w).alias("b"))


@query("op_win_nth", "SELECT event_id, nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM events")
def win_nth(spark, d):
    w = W.partitionBy("user_id").orderBy("event_id").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return table(spark, d, "events").select("event_id", F.nth_value("event_id", 2).over(w).alias("second"))


@query("op_sort_multi", "SELECT row_number() OVER (ORDER BY c_mktsegment DESC, c_acctbal, c_custkey) AS at, c_custkey FROM customer")
def sort_multi(spark, d):
    c = table(spark, d, "customer")
    return row_numbers(c, [F.desc("c_mktsegment"), F.asc("c_acctbal"), F.asc("c_custkey")], "at", c.count()).select(F.col("at").cast("long").alias("at"), "c_custkey")


@query("op_topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
def topk_global(spark, d):
    return table(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25)


@query("op_topk_group", "SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 3")
def topk_group(spark, d):
    w = W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return table(spark, d, "orders").withColumn("r", F.row_number().over(w)).where("r <= 3").select("o_custkey", "o_orderkey")


@query("op_limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 20 OFFSET 40")
def limit_offset(spark, d):
    return table(spark, d, "orders").select("o_orderkey").orderBy("o_orderkey").offset(40).limit(20)


@query("op_set_union", "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier")
def set_union(spark, d):
    return table(spark, d, "customer").select(F.col("c_nationkey").alias("k")).unionByName(table(spark, d, "supplier").select(F.col("s_nationkey").alias("k"))).distinct()


@query("op_set_intersect", "SELECT l_partkey AS k FROM lineitem WHERE l_quantity < 3 INTERSECT SELECT l_partkey FROM lineitem WHERE l_quantity > 48")
def set_intersect(spark, d):
    t = table(spark, d, "lineitem")
    return t.where("l_quantity < 3").select(F.col("l_partkey").alias("k")).intersect(t.where("l_quantity > 48").select(F.col("l_partkey").alias("k")))


@query("op_set_except", "SELECT l_suppkey AS k FROM lineitem WHERE l_quantity < 10 EXCEPT ALL SELECT l_suppkey FROM lineitem WHERE l_quantity > 43")
def set_except(spark, d):
    t = table(spark, d, "lineitem")
    return t.where("l_quantity < 10").select(F.col("l_suppkey").alias("k")).exceptAll(t.where("l_quantity > 43").select(F.col("l_suppkey").alias("k")))


@query("op_distinct", "SELECT DISTINCT md5(text) AS h FROM documents")
def distinct(spark, d):
    return table(spark, d, "documents").select(F.md5("text").alias("h")).distinct()


@query("op_math", "SELECT event_id, round(log10(value + 1), 8) AS a, round(sqrt(value), 8) AS b, round(pow(value, 1.5), 4) AS c, round(sin(value), 8) AS s, floor(value) AS f FROM events")
def math(spark, d):
    v = F.col("value")
    return table(spark, d, "events").select("event_id", F.round(F.log10(v + 1), 8).alias("a"), F.round(F.sqrt(v), 8).alias("b"), F.round(F.pow(v, 1.5), 4).alias("c"), F.round(F.sin(v), 8).alias("s"), F.floor(v).alias("f"))


@query("op_bits", "SELECT o_orderkey, (o_orderkey >> 3) & 255 AS a, CAST(bit_count(o_orderkey) AS INTEGER) AS b, o_orderkey << 4 AS c FROM orders")
def bits(spark, d):
    k = F.col("o_orderkey")
    return table(spark, d, "orders").select("o_orderkey", F.shiftright(k, 3).bitwiseAND(F.lit(255)).alias("a"), F.bit_count(k).alias("b"), F.shiftleft(k, 4).alias("c"))


@query("op_hash", f"SELECT {LINE5.sql_key} AS h FROM lineitem")
def hashed(spark, d):
    return table(spark, d, "lineitem").selectExpr(f"{LINE5.key} AS h")


@query("op_string", "SELECT doc_id, length(text) AS n, len(string_split(text, ' ')) AS words, lower(substr(text, 1, 5)) AS head, regexp_matches(text, '[0-9]{4}') AS digits FROM documents")
def string(spark, d):
    t = F.col("text")
    return table(spark, d, "documents").select("doc_id", F.length(t).cast("long").alias("n"), F.size(F.split(t, " ")).cast("long").alias("words"), F.lower(F.substring(t, 1, 5)).alias("head"), t.rlike("[0-9]{4}").alias("digits"))


@query("op_date", "SELECT o_orderkey, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS day, CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS VARCHAR) AS month, extract(year FROM o_orderdate) AS year FROM orders")
def date(spark, d):
    t = F.to_date("o_orderdate")
    return table(spark, d, "orders").select("o_orderkey", F.datediff(t, F.lit("1992-01-01")).cast("long").alias("day"), F.to_date(F.date_trunc("month", "o_orderdate")).cast("string").alias("month"), F.year(t).cast("long").alias("year"))


@query("op_array", "SELECT vec_id, round(list_sum(list_transform(CAST(embedding AS DOUBLE[]), lambda x: x * x)), 5) AS norm, round(CAST(embedding[1] AS DOUBLE) - CAST(embedding[2] AS DOUBLE), 5) AS diff, len(embedding) AS n FROM embeddings")
def array(spark, d):
    v = F.transform("embedding", lambda x: x.cast("double"))
    return table(spark, d, "embeddings").select("vec_id", F.round(F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x), 5).alias("norm"), F.round(v[0] - v[1], 5).alias("diff"), F.size("embedding").cast("long").alias("n"))


@query("op_map", "SELECT lang, round(avg((length(text) - length(replace(text, 'e', ''))) * 1.0 / length(text)), 8) AS e, round(avg((length(text) - length(replace(text, 'n', ''))) * 1.0 / length(text)), 8) AS n FROM documents GROUP BY lang")
def mapped(spark, d):
    t = table(spark, d, "documents")
    share = lambda x: _share((F.length("text") - F.length(F.replace("text", F.lit(x), F.lit("")))) * 1.0, F.length("text"))
    m = F.map_from_arrays(F.array(F.lit("e"), F.lit("n")), F.array(share("e"), share("n")))
    per = t.select("lang", F.transform_values(m, lambda k, v: v * 1.0).alias("m"))
    return per.groupBy("lang").agg(F.round(F.avg(F.col("m")["e"]), 8).alias("e"), F.round(F.avg(F.col("m")["n"]), 8).alias("n"))


@query("op_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events")
def json(spark, d):
    return table(spark, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("op_struct", "SELECT l_returnflag, min(l_quantity) AS lo, max(l_quantity) AS hi FROM lineitem GROUP BY l_returnflag")
def struct(spark, d):
    b = table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.struct(F.min("l_quantity").alias("lo"), F.max("l_quantity").alias("hi")).alias("box"))
    return b.select("l_returnflag", "box.lo", "box.hi")


_UP = "c AS (SELECT c_custkey AS cell, c_custkey // 3 AS parent FROM customer WHERE c_custkey > 0)"


@query("op_recursive", f"WITH RECURSIVE {_UP}, up(cell, top, depth) AS (SELECT cell, parent, 1 FROM c UNION ALL SELECT up.cell, c.parent, depth + 1 FROM up JOIN c ON up.top = c.cell) SELECT top AS peak, depth, count(*) AS n FROM up GROUP BY ALL")
def recursive(spark, d):
    """A forest of parents over a whole table, followed upwards step by step. A step keeps a count for each place reached,
    not the paths, and parents are below their cells, so the steps end."""
    forest = staged(table(spark, d, "customer").where("c_custkey > 0").select(F.col("c_custkey").cast("long").alias("cell"), F.expr("c_custkey DIV 3").cast("long").alias("parent")), "forest")
    up = staged(forest.groupBy(F.col("parent").alias("peak")).agg(F.count("*").alias("n")), "up")
    out, depth = up.select("peak", F.lit(1).alias("depth"), "n"), 1
    while not (up := staged(up.join(forest, F.col("peak") == F.col("cell")).groupBy(F.col("parent").alias("peak")).agg(F.sum("n").alias("n")), "up")).isEmpty():
        depth += 1
        out = out.unionByName(up.select("peak", F.lit(depth).alias("depth"), "n"))
    return out


@query("op_sample_block")
def sample_block(spark, d):
    """A tenth of the blocks of a table laid out by price: whole blocks come or don't, so the sample is lumpy."""
    layout = kept(spark, d, ("blocks",), lambda: block_layout(LINE3.frame(spark, d), "x0", 50))
    chosen = layout.where(F.pmod(F.xxhash64("block", F.lit(5)), F.lit(10)) == 0)
    return chosen.groupBy("block").agg(F.count("*").alias("n"), F.min("x0").alias("lo"), F.max("x0").alias("hi"))


@query("op_udaf", "SELECT l_returnflag, l_linestatus, round(quantile_cont(l_extendedprice, 0.5), 4) AS middle, count(*) AS n FROM lineitem GROUP BY ALL")
def udaf(spark, d):
    """An aggregate written in Python over Arrow columns: the median of each group."""
    def middle(v: pd.Series) -> float:
        return float(v.median())

    f = F.pandas_udf(middle, "double")
    t = table(spark, d, "lineitem")
    return t.groupBy("l_returnflag", "l_linestatus").agg(f("l_extendedprice").alias("m")).join(t.groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n")), ["l_returnflag", "l_linestatus"]).select("l_returnflag", "l_linestatus", F.round("m", 4).alias("middle"), "n")


@query("op_sample_row")
def sample_row(spark, d):
    table(spark, d, "lineitem").createOrReplaceTempView("cs_lineitem")
    return spark.sql("SELECT count(*) AS n, avg(l_quantity) AS q FROM cs_lineitem TABLESAMPLE (10 PERCENT) REPEATABLE (5)")


@query("op_udf_arrow")
def udf_arrow(spark, d):
    from cellspace.functions.sql_functions import leaf_udf

    index, tree = kd(spark, d, LINE5, 8)
    f = leaf_udf(tree)
    return index.select(f(*LINE5.cols).alias("found"), "leaf").groupBy((F.col("found") == F.col("leaf")).alias("same")).agg(F.count("*").alias("n"))


@query("op_udtf", "WITH RECURSIVE h(h) AS (SELECT 0 UNION ALL SELECT h + 1 FROM h WHERE h < 4) SELECT 2 * last_leaf - bit_count(last_leaf) + 1 + h AS node_id, CAST(h AS INTEGER) AS height, first_leaf, last_leaf FROM (SELECT h, (n << h) AS first_leaf, ((n + 1) << h) - 1 AS last_leaf FROM h, range(16) AS r(n) WHERE n < (16 >> h))")
def table_function(spark, d):
    from cellspace.functions.sql_functions import register

    register(spark)
    return spark.sql("SELECT node_id, height, first_leaf, last_leaf FROM kd_nodes(4)")
