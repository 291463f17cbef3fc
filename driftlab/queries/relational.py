"""Surrounding operators: each with an exact SQL twin over whole tables."""

from __future__ import annotations


import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..session import shared_folder
from ..sources.tables import hash_fraction, read, stratified, table, write
from . import query

LISTED = ("src1", "src2")


def _t(spark: SparkSession, d: str, *names: str) -> list[DataFrame]:
    return [table(spark, d, n) for n in names]


@query("""SELECT l_orderkey, l_partkey, l_suppkey, round(l_extendedprice * (1 - l_discount), 4) AS net, l_returnflag FROM lineitem
          WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R') AND l_discount > 0.05""")
def op_project_filter(spark, d):
    (li,) = _t(spark, d, "lineitem")
    return li.where(F.col("l_quantity").between(10, 20) & F.col("l_returnflag").isin("A", "R") & (F.col("l_discount") > 0.05)).select("l_orderkey", "l_partkey", "l_suppkey", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"), "l_returnflag")


@query("SELECT p_partkey, p_name, p_type FROM part WHERE p_name LIKE '%a%' AND regexp_matches(p_type, '^[A-Z]+ ') AND p_size IS NOT NULL")
def op_like_rlike(spark, d):
    (p,) = _t(spark, d, "part")
    return p.where(F.col("p_name").like("%a%") & F.col("p_type").rlike("^[A-Z]+ ") & F.col("p_size").isNotNull()).select("p_partkey", "p_name", "p_type")


@query("SELECT l_orderkey, l_linenumber, l_partkey, o_custkey, o_totalprice FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def op_join_inner(spark, d):
    li, o = _t(spark, d, "lineitem", "orders")
    return li.join(o, li.l_orderkey == o.o_orderkey).select("l_orderkey", "l_linenumber", "l_partkey", "o_custkey", "o_totalprice")


@query("SELECT c_custkey, c_name, o_orderkey FROM customer LEFT JOIN orders ON c_custkey = o_custkey")
def op_join_left(spark, d):
    c, o = _t(spark, d, "customer", "orders")
    return c.join(o, c.c_custkey == o.o_custkey, "left").select("c_custkey", "c_name", "o_orderkey")


@query("SELECT l.doc_id AS label_id, quality, d.doc_id FROM labels l RIGHT JOIN documents d ON l.doc_id = d.doc_id")
def op_join_right(spark, d):
    lab, doc = _t(spark, d, "labels", "documents")
    return lab.alias("l").join(doc.alias("d"), F.col("l.doc_id") == F.col("d.doc_id"), "right").select(F.col("l.doc_id").alias("label_id"), "quality", "d.doc_id")


@query("""WITH a AS (SELECT l_shipdate::DATE AS day, count(*) AS shipped FROM lineitem GROUP BY 1), b AS (SELECT o_orderdate::DATE AS day, count(*) AS ordered FROM orders GROUP BY 1)
          SELECT coalesce(a.day, b.day)::VARCHAR AS day, coalesce(shipped, 0) AS shipped, coalesce(ordered, 0) AS ordered FROM a FULL JOIN b ON a.day = b.day""")
def op_join_full(spark, d):
    li, o = _t(spark, d, "lineitem", "orders")
    a = li.groupBy(F.to_date("l_shipdate").alias("day")).agg(F.count("*").alias("shipped"))
    b = o.groupBy(F.to_date("o_orderdate").alias("day")).agg(F.count("*").alias("ordered"))
    return a.join(b, "day", "full").select(F.col("day").cast("string").alias("day"), F.coalesce("shipped", F.lit(0)).alias("shipped"), F.coalesce("ordered", F.lit(0)).alias("ordered"))


@query("SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def op_join_broadcast(spark, d):
    n, r = _t(spark, d, "nation", "region")
    return n.join(F.broadcast(r), n.n_regionkey == r.r_regionkey).select("n_name", "r_name")


_CUSTOMER_ORDERS = "SELECT c_mktsegment, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment"


def _customer_orders(spark, d, hint: str) -> DataFrame:
    o, c = _t(spark, d, "orders", "customer")
    return o.hint(hint).join(c, o.o_custkey == c.c_custkey).groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@query(_CUSTOMER_ORDERS)
def op_join_merge(spark, d):
    return _customer_orders(spark, d, "merge")


@query(_CUSTOMER_ORDERS)
def op_join_shuffle_hash(spark, d):
    return _customer_orders(spark, d, "shuffle_hash")


@query("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 400000)")
def op_semi(spark, d):
    c, o = _t(spark, d, "customer", "orders")
    big = o.where("o_totalprice > 400000")
    return c.join(big, c.c_custkey == big.o_custkey, "left_semi").select("c_custkey")


@query("SELECT doc_id FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)")
def op_anti(spark, d):
    doc, lab = _t(spark, d, "documents", "labels")
    return doc.join(lab, "doc_id", "left_anti").select("doc_id")


_FOUR = ((0, 0.25, 0.25), (1, 0.25, 0.75), (2, 0.75, 0.25), (3, 0.75, 0.75))
_FOUR_SQL = "(VALUES (0, 0.25, 0.25), (1, 0.25, 0.75), (2, 0.75, 0.25), (3, 0.75, 0.75)) c(bin, cx, cy)"


@query(f"""WITH p AS (SELECT l_orderkey, l_linenumber, l_partkey, l_quantity / 50 AS x, l_extendedprice / 105000 AS y FROM lineitem),
           r AS (SELECT l_orderkey, l_linenumber, l_partkey, x, y, arg_min(bin, ((x - cx) * (x - cx) + (y - cy) * (y - cy), bin)) AS bin FROM p, {_FOUR_SQL} GROUP BY ALL)
           SELECT bin, count(*) AS n FROM r GROUP BY bin""")
def op_cross_topk(spark, d):
    (li,) = _t(spark, d, "lineitem")
    p = li.select("l_orderkey", "l_linenumber", "l_partkey", (F.col("l_quantity") / 50).alias("x"), (F.col("l_extendedprice") / 105000).alias("y"))
    c = spark.createDataFrame(_FOUR, "bin int, cx double, cy double")
    gap = (F.col("x") - F.col("cx")) * (F.col("x") - F.col("cx")) + (F.col("y") - F.col("cy")) * (F.col("y") - F.col("cy"))
    near = p.crossJoin(F.broadcast(c)).groupBy("l_orderkey", "l_linenumber", "l_partkey", "x", "y").agg(F.min_by("bin", F.struct(gap, F.col("bin"))).alias("bin"))
    return near.groupBy("bin").agg(F.count("*").alias("n"))


_BANDS = ((0, 0.0, 100000.0), (1, 50000.0, 200000.0), (2, 200000.0, 500001.0))


@query("SELECT band, count(*) AS n, round(avg(o_totalprice), 4) AS mean FROM orders JOIN (VALUES (0, 0.0, 100000.0), (1, 50000.0, 200000.0), (2, 200000.0, 500001.0)) b(band, lo, hi) ON o_totalprice >= lo AND o_totalprice < hi GROUP BY band")
def op_range_join(spark, d):
    """Bands are cut to buckets of equal width first, so the join is an equi join on the bucket with the range as a residue."""
    (o,) = _t(spark, d, "orders")
    width = 50000.0
    bands = spark.createDataFrame(_BANDS, "band int, lo double, hi double")
    bands = bands.withColumn("bucket", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor(F.col("hi") / width))))
    rows = o.withColumn("bucket", F.floor(F.col("o_totalprice") / width))
    got = rows.join(bands, "bucket").where((F.col("o_totalprice") >= F.col("lo")) & (F.col("o_totalprice") < F.col("hi")))
    return got.groupBy("band").agg(F.count("*").alias("n"), F.round(F.avg("o_totalprice"), 4).alias("mean"))


@query("""SELECT day, count(*) AS n FROM events JOIN (SELECT unnest(range(0, 30, 3)) AS day) w
          ON ts >= TIMESTAMP '2024-01-01' + to_days(day::INTEGER) AND ts < TIMESTAMP '2024-01-01' + to_days((day + 2)::INTEGER) GROUP BY day""")
def op_interval_join(spark, d):
    (e,) = _t(spark, d, "events")
    w = spark.range(0, 30, 3).select(F.col("id").alias("day"))
    at = F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date"))
    # the days of each window are listed, so the join is by day
    days = w.withColumn("at", F.explode(F.sequence(F.col("day"), F.col("day") + 1)))
    return e.withColumn("at", at.cast("long")).join(F.broadcast(days), "at").groupBy("day").agg(F.count("*").alias("n"))


@query("""SELECT version, count(*) AS n FROM events e ASOF JOIN (VALUES (1, TIMESTAMP '2024-01-01'), (2, TIMESTAMP '2024-01-10 06:00:00'), (3, TIMESTAMP '2024-01-20 12:30:00')) v(version, since) ON e.ts >= v.since GROUP BY version""")
def op_asof_join(spark, d):
    """The version in force at each event: versions are few and broadcast, the latest of those not after the event is kept."""
    (e,) = _t(spark, d, "events")
    v = spark.sql("SELECT * FROM VALUES (1, TIMESTAMP_NTZ '2024-01-01 00:00:00'), (2, TIMESTAMP_NTZ '2024-01-10 06:00:00'), (3, TIMESTAMP_NTZ '2024-01-20 12:30:00') AS v(version, since)")
    return e.join(F.broadcast(v), F.col("ts") >= F.col("since")).groupBy("event_id").agg(F.max_by("version", "since").alias("version")).groupBy("version").agg(F.count("*").alias("n"))


@query("""SELECT a.s_suppkey, min(abs(a.s_acctbal - b.s_acctbal)) AS gap FROM supplier a JOIN supplier b ON a.s_suppkey <> b.s_suppkey GROUP BY a.s_suppkey""")
def op_self_nn(spark, d):
    """In one dimension the nearest neighbour is next in sorted order. Rows are sorted within ranges; a range's first and last
    rows meet the nearest rows of the ranges beside it through a table of one row per range, so nothing is sorted in one task."""
    (s,) = _t(spark, d, "supplier")
    rows = s.select("s_suppkey", "s_acctbal", F.floor(F.col("s_acctbal") / 500).alias("cell"))
    inner = Window.partitionBy("cell").orderBy("s_acctbal", "s_suppkey")
    across = Window.orderBy("cell")
    edges = rows.groupBy("cell").agg(F.min("s_acctbal").alias("low"), F.max("s_acctbal").alias("high"))
    edges = edges.select("cell", F.lag("high").over(across).alias("below"), F.lead("low").over(across).alias("above"))
    near = F.least(F.col("s_acctbal") - F.coalesce(F.lag("s_acctbal").over(inner), "below"), F.coalesce(F.lead("s_acctbal").over(inner), "above") - F.col("s_acctbal"))
    return rows.join(F.broadcast(edges), "cell").select("s_suppkey", near.alias("gap"))


@query("""SELECT user_id, event_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id) AS r FROM events) WHERE r <= 3""")
def op_lateral_topk(spark, d):
    """For each user a correlated subquery of its three newest events.

    The subquery returns ts too: Spark's rewriting of a correlated LIMIT keeps an order only if all its columns are returned, and else takes any three rows.
    """
    (e,) = _t(spark, d, "events")
    e.createOrReplaceTempView("driftlab_events")
    return spark.sql("""SELECT u.user_id, t.event_id FROM (SELECT DISTINCT user_id FROM driftlab_events) u,
        LATERAL (SELECT event_id, ts FROM driftlab_events e WHERE e.user_id <=> u.user_id ORDER BY ts DESC, event_id LIMIT 3) t""")


@query("""SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_extendedprice), 4) AS price, min(l_discount) AS low, max(l_discount) AS high FROM lineitem GROUP BY ALL""")
def op_agg_basic(spark, d):
    (li,) = _t(spark, d, "lineitem")
    return li.groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_extendedprice"), 4).alias("price"), F.min("l_discount").alias("low"), F.max("l_discount").alias("high"))


@query("SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS supps FROM lineitem GROUP BY l_returnflag")
def op_agg_distinct(spark, d):
    (li,) = _t(spark, d, "lineitem")
    return li.groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("supps"))


@query("SELECT l_returnflag, count(*) FILTER (WHERE l_quantity > 25) AS many, round(sum(l_tax) FILTER (WHERE l_discount = 0), 4) AS tax FROM lineitem GROUP BY l_returnflag HAVING count(*) > 1")
def op_agg_filter(spark, d):
    (li,) = _t(spark, d, "lineitem")
    got = li.groupBy("l_returnflag").agg(F.count_if(F.col("l_quantity") > 25).alias("many"), F.round(F.sum(F.when(F.col("l_discount") == 0, F.col("l_tax"))), 4).alias("tax"), F.count("*").alias("n"))
    return got.where("n > 1").drop("n")


@query("SELECT p_brand, arg_min(p_partkey, (p_retailprice, p_partkey)) AS cheapest, arg_max(p_partkey, (p_retailprice, p_partkey)) AS dearest FROM part GROUP BY p_brand")
def op_agg_argmin(spark, d):
    (p,) = _t(spark, d, "part")
    by = F.struct("p_retailprice", "p_partkey")
    return p.groupBy("p_brand").agg(F.min_by("p_partkey", by).alias("cheapest"), F.max_by("p_partkey", by).alias("dearest"))


@query("SELECT o_orderpriority, round(quantile_cont(o_totalprice, 0.5), 4) AS p50, round(quantile_cont(o_totalprice, 0.9), 4) AS p90 FROM orders GROUP BY 1")
def op_percentiles(spark, d):
    (o,) = _t(spark, d, "orders")
    return o.groupBy("o_orderpriority").agg(F.round(F.percentile("o_totalprice", 0.5), 4).alias("p50"), F.round(F.percentile("o_totalprice", 0.9), 4).alias("p90"))


@query("""SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS sd, round(var_pop(l_quantity), 6) AS v, round(corr(l_quantity, l_extendedprice), 6) AS r, round(covar_pop(l_quantity, l_tax), 6) AS c FROM lineitem GROUP BY 1""")
def op_moments(spark, d):
    (li,) = _t(spark, d, "lineitem")
    return li.groupBy("l_returnflag").agg(F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.var_pop("l_quantity"), 6).alias("v"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"), F.round(F.covar_pop("l_quantity", "l_tax"), 6).alias("c"))


@query("SELECT true AS within FROM events LIMIT 1")
def op_approx_distinct(spark, d):
    """Whether the sketch of distinct users is within 5 percent of the exact number."""
    (e,) = _t(spark, d, "events")
    return e.agg((F.abs(F.approx_count_distinct("user_id", 0.02) - F.countDistinct("user_id")) <= 0.05 * F.countDistinct("user_id") + 1).alias("within"))


@query("SELECT true AS within")
def op_approx_percentile(spark, d):
    """Whether the sketch of the median price has a rank within 1 percent of one half."""
    (li,) = _t(spark, d, "lineitem")
    mid = li.agg(F.percentile_approx("l_extendedprice", 0.5, 10000).alias("mid"))
    return li.crossJoin(F.broadcast(mid)).agg((F.abs(F.avg((F.col("l_extendedprice") <= F.col("mid")).cast("int")) - 0.5) < 0.01).alias("within"))


@query("SELECT count(*) AS n, true AS within FROM lineitem")
def op_kll_sketch(spark, d):
    """Whether the KLL sketch of the median price has a rank within 2 percent of one half."""
    (li,) = _t(spark, d, "lineitem")
    mid = li.agg(F.kll_sketch_get_quantile_double(F.kll_sketch_agg_double("l_extendedprice"), F.lit(0.5)).alias("mid"))
    return li.crossJoin(F.broadcast(mid)).agg(F.count("*").alias("n"), (F.abs(F.avg((F.col("l_extendedprice") <= F.col("mid")).cast("int")) - 0.5) < 0.02).alias("within"))


@query("SELECT count(*)::DOUBLE AS n, 10 AS bins FROM events")
def op_histogram_numeric(spark, d):
    (e,) = _t(spark, d, "events")
    h = e.agg(F.histogram_numeric("value", F.lit(10)).alias("h"))
    return h.select(F.aggregate("h", F.lit(0.0), lambda s, b: s + b["y"]).alias("n"), F.size("h").alias("bins"))


_RNC = "FROM region JOIN nation ON r_regionkey = n_regionkey JOIN customer ON n_nationkey = c_nationkey"


def _rnc(spark, d) -> DataFrame:
    r, n, c = _t(spark, d, "region", "nation", "customer")
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))


@query(f"SELECT r_name, n_name, count(*) AS n, round(sum(c_acctbal), 2) AS bal, grouping(r_name, n_name) AS level {_RNC} GROUP BY ROLLUP (r_name, n_name)")
def op_rollup(spark, d):
    return _rnc(spark, d).rollup("r_name", "n_name").agg(F.count("*").alias("n"), F.round(F.sum("c_acctbal"), 2).alias("bal"), F.grouping_id().alias("level"))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, grouping(l_returnflag, l_linestatus) AS level FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def op_cube(spark, d):
    (li,) = _t(spark, d, "lineitem")
    return li.cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.grouping_id().alias("level"))


@query(f"SELECT r_name, c_mktsegment, count(*) AS n {_RNC} GROUP BY GROUPING SETS ((r_name), (c_mktsegment), ())")
def op_grouping_sets(spark, d):
    got = _rnc(spark, d)
    return got.groupingSets([["r_name"], ["c_mktsegment"], []], "r_name", "c_mktsegment").agg(F.count("*").alias("n"))


_TYPES_SQL = "SELECT DISTINCT event_type FROM events"


@query("""SELECT * FROM (SELECT ts::DATE::VARCHAR AS day, event_type FROM events) PIVOT (count(*) FOR event_type IN ('click', 'purchase', 'view', 'signup', 'logout'))""")
def op_pivot(spark, d):
    (e,) = _t(spark, d, "events")
    return e.groupBy(F.to_date("ts").cast("string").alias("day")).pivot("event_type", ["click", "purchase", "view", "signup", "logout"]).agg(F.count(F.lit(1))).na.fill(0)


@query("SELECT l_orderkey, l_linenumber, l_partkey, name, value FROM lineitem UNPIVOT (value FOR name IN (l_discount, l_tax))")
def op_unpivot(spark, d):
    (li,) = _t(spark, d, "lineitem")
    return li.unpivot(["l_orderkey", "l_linenumber", "l_partkey"], ["l_discount", "l_tax"], "name", "value")


_W = "WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)"


def _ordered() -> Window:
    return Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")


@query("""SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER p AS rk, dense_rank() OVER p AS dr FROM orders
          WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey), p AS (PARTITION BY o_custkey ORDER BY o_orderpriority)""")
def op_rank(spark, d):
    (o,) = _t(spark, d, "orders")
    p = Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return o.select("o_orderkey", F.row_number().over(_ordered()).cast("long").alias("rn"), F.rank().over(p).cast("long").alias("rk"), F.dense_rank().over(p).cast("long").alias("dr"))


@query("SELECT p_partkey, ntile(4) OVER (PARTITION BY p_brand ORDER BY p_retailprice, p_partkey) AS q FROM part")
def op_ntile(spark, d):
    (p,) = _t(spark, d, "part")
    return p.select("p_partkey", F.ntile(4).over(Window.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey")).cast("long").alias("q"))


@query(f"SELECT o_orderkey, lag(o_totalprice) OVER w AS before, lead(o_orderkey, 2) OVER w AS after FROM orders {_W}")
def op_lag_lead(spark, d):
    (o,) = _t(spark, d, "orders")
    return o.select("o_orderkey", F.lag("o_totalprice").over(_ordered()).alias("before"), F.lead("o_orderkey", 2).over(_ordered()).alias("after"))


@query(f"SELECT o_orderkey, round(sum(o_totalprice) OVER (w ROWS UNBOUNDED PRECEDING), 2) AS upto FROM orders {_W}")
def op_running_sum(spark, d):
    (o,) = _t(spark, d, "orders")
    return o.select("o_orderkey", F.round(F.sum("o_totalprice").over(_ordered().rowsBetween(Window.unboundedPreceding, Window.currentRow)), 2).alias("upto"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS n FROM events")
def op_moving_range(spark, d):
    (e,) = _t(spark, d, "events")
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    return e.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy(us).rangeBetween(-86_400_000_000, 0)).alias("n"))


@query("""SELECT DISTINCT user_id, first_value(event_id) OVER w AS first, last_value(event_id) OVER w AS last FROM events
          WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)""")
def op_first_last(spark, d):
    (e,) = _t(spark, d, "events")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return e.select("user_id", F.first("event_id").over(w).alias("first"), F.last("event_id").over(w).alias("last")).distinct()


@query("SELECT p_partkey, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_retailprice)")
def op_cume(spark, d):
    (p,) = _t(spark, d, "part")
    w = Window.partitionBy("p_brand").orderBy("p_retailprice")
    return p.select("p_partkey", F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def op_sort_limit(spark, d):
    (o,) = _t(spark, d, "orders")
    return o.orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey", "o_totalprice")


@query("SELECT c_mktsegment, c_custkey FROM (SELECT *, row_number() OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer) WHERE r <= 5")
def op_topk_group(spark, d):
    (c,) = _t(spark, d, "customer")
    w = Window.partitionBy("c_mktsegment").orderBy(F.desc("c_acctbal"), "c_custkey")
    return c.withColumn("r", F.row_number().over(w)).where("r <= 5").select("c_mktsegment", "c_custkey")


@query("SELECT c_custkey FROM customer ORDER BY c_acctbal, c_custkey LIMIT 10 OFFSET 25")
def op_offset(spark, d):
    (c,) = _t(spark, d, "customer")
    return c.orderBy("c_acctbal", "c_custkey").offset(25).limit(10).select("c_custkey")


@query("SELECT c_nationkey AS k, 'c' AS side FROM customer UNION ALL SELECT s_nationkey, 's' FROM supplier")
def op_union(spark, d):
    c, s = _t(spark, d, "customer", "supplier")
    return c.select(F.col("c_nationkey").alias("k"), F.lit("c").alias("side")).unionByName(s.select(F.lit("s").alias("side"), F.col("s_nationkey").alias("k")))


@query("SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")
def op_intersect(spark, d):
    c, s = _t(spark, d, "customer", "supplier")
    return c.select(F.col("c_nationkey").alias("k")).intersect(s.select("s_nationkey"))


@query("SELECT p_size AS k FROM part EXCEPT SELECT l_linenumber FROM lineitem")
def op_except(spark, d):
    p, li = _t(spark, d, "part", "lineitem")
    return p.select(F.col("p_size").alias("k")).subtract(li.select("l_linenumber"))


@query("SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
def op_except_all(spark, d):
    c, s = _t(spark, d, "customer", "supplier")
    return c.select(F.col("c_nationkey").alias("k")).exceptAll(s.select("s_nationkey"))


@query("""SELECT doc_id, length(text) AS n, md5(text) AS digest, upper(lang) AS lang, substr(text, 1, 5) AS head, instr(text, 'the') AS at, len(string_split(text, ' ')) AS words, lang || '-' || source AS tag, translate(source, 'src', 'SRC') AS tr FROM documents""")
def op_string(spark, d):
    (doc,) = _t(spark, d, "documents")
    return doc.select("doc_id", F.length("text").cast("long").alias("n"), F.md5("text").alias("digest"), F.upper("lang").alias("lang"), F.substring("text", 1, 5).alias("head"), F.instr("text", "the").cast("long").alias("at"), F.size(F.split("text", " ")).cast("long").alias("words"), F.concat_ws("-", "lang", "source").alias("tag"), F.translate("source", "src", "SRC").alias("tr"))


@query("SELECT doc_id, regexp_extract(source, '([0-9]+)', 1)::INTEGER AS no, length(regexp_replace(lower(text), '[^aeiou]', '', 'g')) AS vowels FROM documents")
def op_regexp(spark, d):
    (doc,) = _t(spark, d, "documents")
    return doc.select("doc_id", F.regexp_extract("source", "([0-9]+)", 1).cast("int").alias("no"), F.length(F.regexp_replace(F.lower("text"), "[^aeiou]", "")).cast("long").alias("vowels"))


@query("SELECT regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, count(*) AS n FROM pages GROUP BY 1")
def op_url_host(spark, d):
    (p,) = _t(spark, d, "pages")
    return p.groupBy(F.regexp_extract("url", "^[a-z]+://([^/:?#]+)", 1).alias("host")).agg(F.count("*").alias("n"))


@query("""SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, date_trunc('month', o_orderdate)::DATE::VARCHAR AS start, date_diff('day', DATE '1995-01-01', o_orderdate::DATE) AS days, (o_orderdate::DATE + INTERVAL 1 MONTH)::DATE::VARCHAR AS next FROM orders""")
def op_date(spark, d):
    (o,) = _t(spark, d, "orders")
    day = F.to_date("o_orderdate")
    return o.select("o_orderkey", F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m"), F.to_date(F.date_trunc("month", "o_orderdate")).cast("string").alias("start"), F.datediff(day, F.lit("1995-01-01").cast("date")).cast("long").alias("days"), F.add_months(day, 1).cast("string").alias("next"))


@query("""SELECT event_id, round(sqrt(value), 6) AS r, round(ln(value + 1), 6) AS l, round(exp(-value / 100), 6) AS e, floor(value)::BIGINT AS f, greatest(value, 50) AS g, least(value, 50) AS s, round(cos(value), 6) AS c FROM events""")
def op_math(spark, d):
    (e,) = _t(spark, d, "events")
    v = F.col("value")
    return e.select("event_id", F.round(F.sqrt(v), 6).alias("r"), F.round(F.log(v + 1), 6).alias("l"), F.round(F.exp(-v / 100), 6).alias("e"), F.floor(v).cast("long").alias("f"), F.greatest(v, F.lit(50.0)).alias("g"), F.least(v, F.lit(50.0)).alias("s"), F.round(F.cos(v), 6).alias("c"))


@query("""SELECT CASE WHEN l_extendedprice < 0 THEN 0 WHEN l_extendedprice >= 110000 THEN 12 ELSE floor(l_extendedprice / 10000)::BIGINT + 1 END AS bucket, count(*) AS n FROM lineitem GROUP BY 1""")
def op_bucket(spark, d):
    (li,) = _t(spark, d, "lineitem")
    return li.groupBy(F.width_bucket("l_extendedprice", F.lit(0.0), F.lit(110000.0), F.lit(11)).alias("bucket")).agg(F.count("*").alias("n"))


@query("""SELECT vec_id, len(embedding)::INTEGER AS n, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 5) AS norm2, round(list_max(embedding)::DOUBLE, 6) AS top, list_position(embedding, list_max(embedding))::BIGINT AS at, round(list_sum(list_transform(embedding[1:4], lambda x: x::DOUBLE)), 5) AS head FROM embeddings""")
def op_array(spark, d):
    (e,) = _t(spark, d, "embeddings")
    add = lambda c: F.aggregate(c, F.lit(0.0), lambda s, x: s + x)
    real = F.transform("embedding", lambda x: x.cast("double"))
    return e.select("vec_id", F.size("embedding").alias("n"), F.round(add(F.transform(real, lambda x: x * x)), 5).alias("norm2"), F.round(F.array_max(real), 6).alias("top"), F.array_position("embedding", F.array_max("embedding")).alias("at"), F.round(add(F.slice(real, 1, 4)), 5).alias("head"))


@query("SELECT event_id, event_type || ':' || user_id AS pair, 2 AS n FROM events")
def op_map(spark, d):
    (e,) = _t(spark, d, "events")
    m = F.create_map(F.lit("type"), F.col("event_type"), F.lit("user"), F.col("user_id").cast("string"))
    return e.select("event_id", F.concat_ws(":", F.element_at(m, "type"), F.element_at(m, "user")).alias("pair"), F.size(F.map_keys(m)).alias("n"))


@query("SELECT event_id, (props->>'$.k')::INTEGER AS k FROM events")
def op_json(spark, d):
    (e,) = _t(spark, d, "events")
    return e.select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("SELECT c_nationkey, max(c_acctbal) AS bal, arg_max(c_custkey, (c_acctbal, c_custkey)) AS who FROM customer GROUP BY 1")
def op_struct(spark, d):
    (c,) = _t(spark, d, "customer")
    got = c.groupBy("c_nationkey").agg(F.max(F.struct("c_acctbal", "c_custkey")).alias("m"))
    return got.select("c_nationkey", F.col("m.c_acctbal").alias("bal"), F.col("m.c_custkey").alias("who"))


@query("""SELECT conv_id, turn, role, lag(role) OVER (PARTITION BY conv_id ORDER BY turn) AS before, count(*) OVER (PARTITION BY conv_id, role) AS same FROM conversations""")
def op_turn_windows(spark, d):
    (c,) = _t(spark, d, "conversations")
    return c.select("conv_id", "turn", "role", F.lag("role").over(Window.partitionBy("conv_id").orderBy("turn")).alias("before"), F.count("*").over(Window.partitionBy("conv_id", "role")).alias("same"))


_RECURSIVE = """WITH RECURSIVE s AS (SELECT CAST(l_linenumber AS INTEGER) AS k, count(*) AS lines FROM {lineitem} GROUP BY l_linenumber),
    r(n, f) AS (SELECT 1, (SELECT CAST(lines AS BIGINT) FROM s WHERE k = 1) UNION ALL SELECT k, CAST(f + k * lines AS BIGINT) FROM r JOIN s ON k = n + 1) SELECT n, f FROM r"""


@query(_RECURSIVE.format(lineitem="lineitem"))
def op_recursive(spark, d):
    """Sums of line numbers up to each line number of lineitem, one step of the recursion for each."""
    (li,) = _t(spark, d, "lineitem")
    li.createOrReplaceTempView("driftlab_lineitem")
    return spark.sql(_RECURSIVE.format(lineitem="driftlab_lineitem"))


@query("SELECT md5(text) AS digest, min(doc_id) AS keep, count(*) AS n FROM documents GROUP BY 1 HAVING count(*) > 1")
def op_dedup(spark, d):
    (doc,) = _t(spark, d, "documents")
    return doc.groupBy(F.md5("text").alias("digest")).agg(F.min("doc_id").alias("keep"), F.count("*").alias("n")).where("n > 1")


@query("SELECT o_orderkey FROM orders WHERE ('0x' || substr(md5('7:' || o_orderkey), 1, 8))::BIGINT < 1073741824")
def op_sample_hash(spark, d):
    (o,) = _t(spark, d, "orders")
    return hash_fraction(o, 0.25, ["o_orderkey"], 7).select("o_orderkey")


@query("""SELECT doc_id, lang FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY md5('3:' || doc_id), doc_id) AS r FROM documents)
          WHERE (lang = 'en' AND r <= 40) OR (lang = 'fr' AND r <= 20) OR (lang = 'de' AND r <= 10)""")
def op_sample_stratified(spark, d):
    (doc,) = _t(spark, d, "documents")
    return stratified(doc.select("doc_id", "lang"), "lang", {"en": 40, "fr": 20, "de": 10}, ["doc_id"], 3)


@query("SELECT kind, n_nationkey, n_name, n_regionkey FROM nation, (VALUES ('csv'), ('json'), ('orc'), ('parquet')) k(kind)")
def op_sink_roundtrip(spark, d):
    """Writes nation in four formats under the session's shared folder (a temporary one where none is set) and reads it back."""
    (n,) = _t(spark, d, "nation")
    root = shared_folder(spark)
    out = None
    for kind in ("csv", "json", "orc", "parquet"):
        write(n, f"{root}/driftlab-nation-{kind}", kind)
        got = read(spark, f"{root}/driftlab-nation-{kind}", kind, "n_nationkey int, n_name string, n_regionkey int").select(F.lit(kind).alias("kind"), "n_nationkey", "n_name", "n_regionkey")
        out = got if out is None else out.unionByName(got)
    return out


@query("SELECT l_orderkey, l_linenumber, l_partkey, round(l_extendedprice * (1 - l_discount) * (1 + l_tax), 6) AS charge FROM lineitem")
def op_udf(spark, d):
    (li,) = _t(spark, d, "lineitem")

    @F.pandas_udf("double")
    def charge(p: pd.Series, disc: pd.Series, tax: pd.Series) -> pd.Series:
        return p * (1 - disc) * (1 + tax)

    return li.select("l_orderkey", "l_linenumber", "l_partkey", F.round(charge("l_extendedprice", "l_discount", "l_tax"), 6).alias("charge"))


@query("SELECT label, round(avg(embedding[1]::DOUBLE), 5) AS m1, round(avg(embedding[64]::DOUBLE), 5) AS m64 FROM embeddings GROUP BY label")
def op_udaf(spark, d):
    (e,) = _t(spark, d, "embeddings")

    @F.pandas_udf("array<double>")
    def vec_mean(v: pd.Series) -> list[float]:
        return np.stack(v.to_numpy()).mean(axis=0, dtype=float).tolist()

    got = e.groupBy("label").agg(vec_mean(F.col("embedding").cast("array<double>")).alias("m"))
    return got.select("label", F.round(F.col("m")[0], 5).alias("m1"), F.round(F.col("m")[63], 5).alias("m64"))


@query("""WITH w AS (SELECT bin, sum(o)::BIGINT AS o, sum(t)::BIGINT AS t FROM (SELECT l_linenumber AS bin, (year(l_shipdate) < 1998)::INTEGER AS o, (year(l_shipdate) >= 1998)::INTEGER AS t FROM lineitem) GROUP BY bin)
          SELECT round(sum((q * o - n * t) * (q * o - n * t) / (o + t)) / (any_value(n) * any_value(q)), 4) AS stat, (count(*) - 1)::INTEGER AS dof
          FROM w, (SELECT sum(o)::DOUBLE AS n, sum(t)::DOUBLE AS q FROM w)""")
def op_udtf(spark, d):
    from ..functions.sqlfuncs import register_tables

    (li,) = _t(spark, d, "lineitem")
    late = (F.year("l_shipdate") >= 1998).cast("int")
    counts = li.groupBy(F.col("l_linenumber").alias("bin")).agg(F.sum(1 - late).alias("o"), F.sum(late).alias("t"))
    counts.createOrReplaceTempView("op_udtf_counts")
    register_tables(spark)
    return spark.sql("SELECT round(stat, 4) AS stat, dof FROM chi2_report(TABLE(op_udtf_counts) WITH SINGLE PARTITION)")
