"""Relational operators a user needs around the methods, each with DuckDB SQL that gives the same rows.

Entries register by decorator: the function is the Spark plan, the string its SQL.
"""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from ..storage import shared_dir, table, written

OPS: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def op(sql: str | None = None):
    def add(f):
        OPS[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


def _t(spark: SparkSession, d: str, *names: str):
    found = [table(spark, d, n) for n in names]
    return found[0] if len(found) == 1 else found


# ---- projection and filter


@op("SELECT p_partkey, p_size * 2 + 1 AS a, round(p_retailprice * 1.1, 6) AS b, upper(p_type) AS t FROM part")
def op_project_exprs(s, d):
    return _t(s, d, "part").select("p_partkey", (F.col("p_size") * 2 + 1).alias("a"), F.round(F.col("p_retailprice") * 1.1, 6).alias("b"), F.upper("p_type").alias("t"))


@op("SELECT p_partkey, p_retailprice FROM part WHERE p_retailprice BETWEEN 950 AND 1200")
def op_filter_range(s, d):
    return _t(s, d, "part").where(F.col("p_retailprice").between(950, 1200)).select("p_partkey", "p_retailprice")


@op("SELECT p_partkey, p_size FROM part WHERE p_size IN (1, 7, 20)")
def op_filter_in(s, d):
    return _t(s, d, "part").where(F.col("p_size").isin(1, 7, 20)).select("p_partkey", "p_size")


@op("SELECT p_partkey, p_name FROM part WHERE p_name LIKE '%a%' AND regexp_matches(p_brand, '[13]$')")
def op_filter_like(s, d):
    return _t(s, d, "part").where(F.col("p_name").like("%a%") & F.col("p_brand").rlike("[13]$")).select("p_partkey", "p_name")


@op("SELECT d.doc_id, coalesce(l.quality, -1) AS q FROM documents d LEFT JOIN labels l USING (doc_id) WHERE l.toxic IS NULL")
def op_filter_null(s, d):
    docs, labels = _t(s, d, "documents", "labels")
    return docs.select("doc_id").join(labels, "doc_id", "left").where("toxic is null").select("doc_id", F.coalesce("quality", F.lit(-1)).alias("q"))


@op("SELECT p_partkey, (p_partkey * 48271) % 1601 - 800 AS mx, (p_partkey * 16807) % 901 - 450 AS my FROM part WHERE (p_partkey * 48271) % 1601 - 800 BETWEEN -300 AND 300 AND (p_partkey * 16807) % 901 - 450 BETWEEN 0 AND 200")
def op_bbox_filter(s, d):
    p = _t(s, d, "part").select("p_partkey", F.expr("(p_partkey * 48271) % 1601 - 800").alias("mx"), F.expr("(p_partkey * 16807) % 901 - 450").alias("my"))
    return p.where(F.col("mx").between(-300, 300) & F.col("my").between(0, 200))


# ---- joins


@op("SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def op_join_broadcast(s, d):
    c, n, r = _t(s, d, "customer", "nation", "region")  # 25 and 5 rows at any scale
    return c.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey")).select("c_custkey", "n_name", "r_name")


@op("SELECT o_orderkey, l_linenumber, o_custkey, l_partkey FROM orders JOIN lineitem ON o_orderkey = l_orderkey")
def op_join_sortmerge(s, d):
    o, li = _t(s, d, "orders", "lineitem")
    return o.hint("merge").join(li, F.col("o_orderkey") == F.col("l_orderkey")).select("o_orderkey", "l_linenumber", "o_custkey", "l_partkey")


@op("SELECT l_orderkey, l_linenumber, p_brand FROM lineitem JOIN part ON l_partkey = p_partkey")
def op_join_shuffle_hash(s, d):
    li, p = _t(s, d, "lineitem", "part")
    return li.join(p.hint("shuffle_hash"), F.col("l_partkey") == F.col("p_partkey")).select("l_orderkey", "l_linenumber", "p_brand")


@op("SELECT d.doc_id, quality, toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
def op_join_left(s, d):
    docs, labels = _t(s, d, "documents", "labels")
    return docs.select("doc_id").join(labels, "doc_id", "left").select("doc_id", "quality", "toxic")


@op("SELECT c_custkey, o_orderkey FROM orders RIGHT JOIN customer ON o_custkey = c_custkey")
def op_join_right(s, d):
    c, o = _t(s, d, "customer", "orders")
    return o.join(c, F.col("o_custkey") == F.col("c_custkey"), "right").select("c_custkey", "o_orderkey")


@op("""WITH a AS (SELECT p_brand AS val, count(*) AS n FROM part WHERE p_size < 10 GROUP BY 1), b AS (SELECT p_brand AS val, count(*) AS n FROM part WHERE p_size > 45 GROUP BY 1)
SELECT coalesce(a.val, b.val) AS val, coalesce(a.n, 0) + coalesce(b.n, 0) AS n FROM a FULL JOIN b ON a.val = b.val""")
def op_join_full(s, d):
    p = _t(s, d, "part")
    a = p.where("p_size < 10").groupBy(F.col("p_brand").alias("val")).agg(F.count("*").alias("n"))
    b = p.where("p_size > 45").groupBy(F.col("p_brand").alias("val")).agg(F.count("*").alias("m"))
    return a.join(b, "val", "full").select("val", (F.coalesce("n", F.lit(0)) + F.coalesce("m", F.lit(0))).alias("n"))


_SESSIONS = "SELECT DISTINCT user_id // 8 AS session_id FROM events"
_CLICKED = "SELECT o_custkey // 8 AS session_id FROM orders"


def _sessions(s, d):
    return _t(s, d, "events").select(F.expr("user_id div 8").alias("session_id")).distinct(), _t(s, d, "orders").select(F.expr("o_custkey div 8").alias("session_id"))


@op(f"SELECT session_id FROM ({_SESSIONS}) WHERE session_id IN ({_CLICKED})")
def op_semi(s, d):
    a, b = _sessions(s, d)
    return a.join(b, "session_id", "left_semi")


@op(f"SELECT session_id FROM ({_SESSIONS}) WHERE session_id NOT IN ({_CLICKED})")
def op_anti_noclick(s, d):
    a, b = _sessions(s, d)
    return a.join(b, "session_id", "left_anti")


@op("""WITH p AS (SELECT p_partkey, (p_partkey * 48271) % 1601 - 800 AS mx, (p_partkey * 16807) % 901 - 450 AS my FROM part),
m AS (SELECT DISTINCT (event_id * 7919) % 1600 - 800 AS x, (event_id * 104729) % 900 - 450 AS y FROM events WHERE value >= 120)
SELECT p_partkey FROM p WHERE NOT EXISTS (SELECT 1 FROM m WHERE (mx - x) * (mx - x) + (my - y) * (my - y) <= 400)""")
def op_anti_outofsight(s, d):
    p = _t(s, d, "part").select("p_partkey", F.expr("(p_partkey * 48271) % 1601 - 800").alias("mx"), F.expr("(p_partkey * 16807) % 901 - 450").alias("my"))
    m = _t(s, d, "events").where("value >= 120").select(F.expr("(event_id * 7919) % 1600 - 800").alias("x"), F.expr("(event_id * 104729) % 900 - 450").alias("y")).distinct()
    off = F.array(*map(F.lit, (-1, 0, 1)))
    # moves go to the nine squares of 20 pixels around them, so a part meets one row and stops at the first move in reach;
    # the hint: Spark's sizes do not count what explode adds, and neither side need fit the driver
    g = m.withColumn("i", F.explode(off)).withColumn("j", F.explode(off)).groupBy((F.floor(F.col("x") / 20) + F.col("i")).alias("gx"), (F.floor(F.col("y") / 20) + F.col("j")).alias("gy")).agg(F.collect_list(F.struct("x", "y")).alias("at"))
    met = p.withColumn("gx", F.floor(F.col("mx") / 20)).withColumn("gy", F.floor(F.col("my") / 20)).join(g.hint("merge"), ["gx", "gy"], "left")
    return met.where("not coalesce(exists(at, q -> (mx - q.x) * (mx - q.x) + (my - q.y) * (my - q.y) <= 400), false)").select("p_partkey")


@op("SELECT b.id, count(*) AS n FROM (VALUES (1, -600, -300), (2, -350, 50), (3, -100, -200)) b(id, x0, y0) JOIN (SELECT (p_partkey * 48271) % 1601 - 800 AS mx, (p_partkey * 16807) % 901 - 450 AS my FROM part) p ON mx BETWEEN x0 AND x0 + 200 AND my BETWEEN y0 AND y0 + 200 GROUP BY b.id")
def op_join_nested(s, d):
    b = s.createDataFrame([(1, -600, -300), (2, -350, 50), (3, -100, -200)], "id int, x0 int, y0 int")
    p = _t(s, d, "part").select(F.expr("(p_partkey * 48271) % 1601 - 800").alias("mx"), F.expr("(p_partkey * 16807) % 901 - 450").alias("my"))
    return p.join(F.broadcast(b), F.expr("mx between x0 and x0 + 200 and my between y0 and y0 + 200")).groupBy("id").agg(F.count("*").alias("n"))


@op("SELECT a.p_partkey AS a, count(*) AS n FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_type = b.p_type AND b.p_retailprice < a.p_retailprice AND b.p_size >= a.p_size GROUP BY 1")
def op_join_theta(s, d):
    p = _t(s, d, "part")
    b = p.select(F.col("p_brand"), F.col("p_type"), F.col("p_retailprice").alias("rp"), F.col("p_size").alias("rs"))
    return p.join(b, ["p_brand", "p_type"]).where("rp < p_retailprice and rs >= p_size").groupBy(F.col("p_partkey").alias("a")).agg(F.count("*").alias("n"))


@op("""WITH m AS (SELECT event_id, user_id // 8 AS session_id, (event_id * 7919) % 1600 - 800 AS x, (event_id * 104729) % 900 - 450 AS y FROM events WHERE value >= 60)
SELECT a.event_id AS a, b.event_id AS b FROM m a JOIN m b ON a.session_id = b.session_id AND a.event_id < b.event_id AND (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) < 900""")
def op_join_range(s, d):
    m = _t(s, d, "events").where("value >= 60").select("event_id", F.expr("user_id div 8").alias("session_id"), F.expr("(event_id * 7919) % 1600 - 800").alias("x"), F.expr("(event_id * 104729) % 900 - 450").alias("y"))
    off = F.array(*map(F.lit, (-1, 0, 1)))
    a = m.withColumn("i", F.explode(off)).withColumn("j", F.explode(off)).select("session_id", F.col("event_id").alias("a"), "x", "y", (F.floor(F.col("x") / 30) + F.col("i")).alias("gx"), (F.floor(F.col("y") / 30) + F.col("j")).alias("gy"))
    b = m.select("session_id", F.col("event_id").alias("b"), F.col("x").alias("u"), F.col("y").alias("v"), F.floor(F.col("x") / 30).alias("gx"), F.floor(F.col("y") / 30).alias("gy"))
    return a.join(b, ["session_id", "gx", "gy"]).where("a < b and (x - u) * (x - u) + (y - v) * (y - v) < 900").select("a", "b")


@op("""WITH seg AS (SELECT s.i AS seg, s.i * 10 AS lo, s.i * 10 + 10 AS hi FROM generate_series(0, 9) s(i)) SELECT event_id, seg FROM events JOIN seg ON value >= lo AND value < hi""")
def op_join_interval(s, d):
    e = _t(s, d, "events").select("event_id", "value").withColumn("b", F.floor(F.col("value") / 10))
    seg = s.range(10).select(F.col("id").alias("seg"), (F.col("id") * 10).alias("lo"), (F.col("id") * 10 + 10).alias("hi"), F.col("id").alias("b"))
    return e.join(F.broadcast(seg), "b").where("value >= lo and value < hi").select("event_id", "seg")


@op("""SELECT e.event_id, p.event_id AS purchase FROM events e ASOF JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'purchase' GROUP BY 1, 2) p ON e.user_id = p.user_id AND e.ts >= p.ts WHERE e.event_type = 'click'""")
def op_join_asof(s, d):
    e = _t(s, d, "events").where("event_type in ('click', 'purchase')")
    w = W.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "purchase", 0).otherwise(1), "event_id").rowsBetween(W.unboundedPreceding, 0)
    last = F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("purchase", last).where("event_type = 'click' and purchase is not null").select("event_id", "purchase")


@op("SELECT a.p_partkey AS a, b.p_partkey AS b FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_type = b.p_type AND a.p_size = b.p_size AND a.p_partkey < b.p_partkey")
def op_join_self(s, d):
    p = _t(s, d, "part").select("p_brand", "p_type", "p_size", F.col("p_partkey").alias("a"))
    return p.join(p.withColumnRenamed("a", "b"), ["p_brand", "p_type", "p_size"]).where("a < b").select("a", "b")


@op("SELECT c_custkey, o.o_orderkey FROM customer, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2) o")
def op_lateral(s, d):
    c, o = _t(s, d, "customer", "orders")
    w = W.partitionBy("o_custkey").orderBy(F.col("o_totalprice").desc(), "o_orderkey")
    top = o.withColumn("r", F.row_number().over(w)).where("r <= 2")
    return c.join(top, F.col("c_custkey") == F.col("o_custkey")).select("c_custkey", "o_orderkey")


@op("SELECT vec_id, i AS dim, round(embedding[i]::DOUBLE, 6) AS v FROM embeddings, generate_series(1, 4) g(i)")
def op_explode(s, d):
    e = _t(s, d, "embeddings")
    return e.select("vec_id", F.posexplode(F.slice("embedding", 1, 4)).alias("p", "x")).select("vec_id", (F.col("p") + 1).cast("long").alias("dim"), F.round(F.col("x").cast("double"), 6).alias("v"))


# ---- aggregates


@op("SELECT p_brand, count(*) AS n, sum(p_size)::BIGINT AS s, max(p_retailprice) AS m FROM part GROUP BY p_brand")
def op_agg_hash(s, d):
    return _t(s, d, "part").groupBy("p_brand").agg(F.count("*").alias("n"), F.sum("p_size").alias("s"), F.max("p_retailprice").alias("m"))


@op("SELECT count(DISTINCT p_brand) AS b, count(DISTINCT p_type) AS t, count(DISTINCT p_size) AS z FROM part")
def op_agg_distinct(s, d):
    return _t(s, d, "part").agg(F.count_distinct("p_brand").alias("b"), F.count_distinct("p_type").alias("t"), F.count_distinct("p_size").alias("z"))


@op()
def op_agg_approx_distinct(s, d):
    return _t(s, d, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


@op("SELECT p_type, string_agg(p_brand, ',' ORDER BY p_brand) AS brands FROM (SELECT DISTINCT p_type, p_brand FROM part) GROUP BY p_type")
def op_agg_collect(s, d):
    return _t(s, d, "part").groupBy("p_type").agg(F.array_join(F.array_sort(F.collect_set("p_brand")), ",").alias("brands"))


@op("SELECT p_brand, arg_min(p_partkey, p_retailprice * 1000000 + p_partkey) AS cheap, arg_max(p_partkey, p_retailprice * 1000000 + p_partkey) AS dear FROM part GROUP BY p_brand")
def op_agg_minby(s, d):
    k = F.col("p_retailprice") * 1000000 + F.col("p_partkey")
    return _t(s, d, "part").groupBy("p_brand").agg(F.min_by("p_partkey", k).alias("cheap"), F.max_by("p_partkey", k).alias("dear"))


@op("SELECT event_type, count(*) FILTER (value >= 120) AS noise, count(*) AS n FROM events GROUP BY event_type")
def op_agg_filter(s, d):
    return _t(s, d, "events").groupBy("event_type").agg(F.count_if(F.col("value") >= 120).alias("noise"), F.count("*").alias("n"))


@op("SELECT p_brand, p_type, count(*) AS n FROM part GROUP BY GROUPING SETS ((p_brand), (p_type), ())")
def op_grouping_sets(s, d):
    _t(s, d, "part").createOrReplaceTempView("roilens_part")
    return s.sql("SELECT p_brand, p_type, count(*) AS n FROM roilens_part GROUP BY GROUPING SETS ((p_brand), (p_type), ())")


@op("SELECT p_brand, p_type, count(*) AS n FROM part GROUP BY CUBE (p_brand, p_type)")
def op_cube(s, d):
    return _t(s, d, "part").cube("p_brand", "p_type").agg(F.count("*").alias("n"))


@op("SELECT r_name, n_name, count(*) AS n FROM nation JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def op_rollup(s, d):
    n, r = _t(s, d, "nation", "region")
    return n.join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey")).rollup("r_name", "n_name").agg(F.count("*").alias("n"))


@op("SELECT p_type, count(*) FILTER ((p_size - 1) // 10 = 0) AS d0, count(*) FILTER ((p_size - 1) // 10 = 1) AS d1, count(*) FILTER ((p_size - 1) // 10 = 4) AS d4 FROM part GROUP BY p_type")
def op_pivot(s, d):
    p = _t(s, d, "part").withColumn("dec", F.expr("(p_size - 1) div 10"))
    out = p.groupBy("p_type").pivot("dec", [0, 1, 4]).agg(F.count("p_partkey"))
    return out.select("p_type", *(F.coalesce(F.col(f"`{i}`"), F.lit(0)).cast("long").alias(f"d{i}") for i in (0, 1, 4)))


@op("SELECT p_partkey, 'brand' AS attr, p_brand AS val FROM part UNION ALL SELECT p_partkey, 'type', p_type FROM part")
def op_unpivot(s, d):
    p = _t(s, d, "part").select("p_partkey", F.col("p_brand").alias("brand"), F.col("p_type").alias("type"))
    return p.unpivot("p_partkey", ["brand", "type"], "attr", "val")


@op("SELECT l_returnflag, round(stddev_pop(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS r FROM lineitem GROUP BY l_returnflag")
def op_stats(s, d):
    return _t(s, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.stddev_pop("l_quantity"), 6).alias("sd"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"))


@op("SELECT event_type, round(quantile_cont(value, 0.5), 6) AS p50, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY event_type")
def op_percentile(s, d):
    return _t(s, d, "events").groupBy("event_type").agg(F.round(F.percentile("value", 0.5), 6).alias("p50"), F.round(F.percentile("value", 0.9), 6).alias("p90"))


@op("SELECT cast(floor(value / 25) AS BIGINT) AS bucket, count(*) AS n FROM events GROUP BY 1")
def op_histogram(s, d):
    return _t(s, d, "events").groupBy(F.floor(F.col("value") / 25).alias("bucket")).agg(F.count("*").alias("n"))


@op("SELECT p_brand, p_type, count(*) AS n FROM part GROUP BY 1, 2 HAVING count(*) > 12")
def op_having(s, d):
    return _t(s, d, "part").groupBy("p_brand", "p_type").agg(F.count("*").alias("n")).where("n > 12")


# ---- windows


def _by_brand():
    return W.partitionBy("p_brand").orderBy("p_size", "p_partkey")


@op("SELECT p_partkey, row_number() OVER (PARTITION BY p_brand ORDER BY p_size, p_partkey) AS rn, rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS rk, dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS dr FROM part")
def op_rank(s, d):
    w = W.partitionBy("p_brand").orderBy("p_size")
    return _t(s, d, "part").select("p_partkey", F.row_number().over(_by_brand()).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"))


@op("SELECT p_partkey, ntile(5) OVER (PARTITION BY p_brand ORDER BY p_size, p_partkey) AS q FROM part")
def op_ntile(s, d):
    return _t(s, d, "part").select("p_partkey", F.ntile(5).over(_by_brand()).alias("q"))


@op("SELECT p_partkey, round(percent_rank() OVER (PARTITION BY p_brand ORDER BY p_size, p_partkey), 6) AS pr FROM part")
def op_percent_rank(s, d):
    return _t(s, d, "part").select("p_partkey", F.round(F.percent_rank().over(_by_brand()), 6).alias("pr"))


@op("SELECT p_partkey, round(cume_dist() OVER (PARTITION BY p_brand ORDER BY p_size, p_partkey), 6) AS cd FROM part")
def op_cume_dist(s, d):
    return _t(s, d, "part").select("p_partkey", F.round(F.cume_dist().over(_by_brand()), 6).alias("cd"))


@op("SELECT p_partkey, lag(p_size) OVER w AS prev, lead(p_size, 2) OVER w AS nxt FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size, p_partkey)")
def op_lag_lead(s, d):
    return _t(s, d, "part").select("p_partkey", F.lag("p_size").over(_by_brand()).alias("prev"), F.lead("p_size", 2).over(_by_brand()).alias("nxt"))


@op("SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY event_id ROWS UNBOUNDED PRECEDING) AS seen FROM events")
def op_first_last_ignore_nulls(s, d):
    w = W.partitionBy("user_id").orderBy("event_id").rowsBetween(W.unboundedPreceding, 0)
    return _t(s, d, "events").select("event_id", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w).alias("seen"))


@op("SELECT p_partkey, nth_value(p_partkey, 2) OVER (PARTITION BY p_brand ORDER BY p_size, p_partkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM part")
def op_nth_value(s, d):
    w = _by_brand().rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return _t(s, d, "part").select("p_partkey", F.nth_value("p_partkey", 2).over(w).alias("second"))


@op("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS m FROM events")
def op_frame_rows(s, d):
    w = W.partitionBy("user_id").orderBy("event_id").rowsBetween(-4, 0)
    return _t(s, d, "events").select("event_id", F.round(F.avg("value").over(w), 6).alias("m"))


@op("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 6 HOUR PRECEDING AND CURRENT ROW) AS n FROM events")
def op_frame_range(s, d):
    e = _t(s, d, "events").withColumn("us", F.expr("cast(cast(cast(ts as timestamp_ntz) - timestamp_ntz'2024-01-01 00:00:00' as interval second) as decimal(20,6)) * 1000000").cast("long"))
    w = W.partitionBy("user_id").orderBy("us").rangeBetween(-6 * 3600 * 1000000, 0)
    return e.select("event_id", F.count("*").over(w).alias("n"))


@op("SELECT event_id, coalesce(sum(CASE WHEN value >= 120 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS n FROM events")
def op_frame_prefix(s, d):
    w = W.partitionBy("user_id").orderBy("event_id").rowsBetween(W.unboundedPreceding, -1)
    return _t(s, d, "events").select("event_id", F.coalesce(F.sum((F.col("value") >= 120).cast("long")).over(w), F.lit(0)).alias("n"))


@op("SELECT event_id, max(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS m FROM events")
def op_frame_suffix(s, d):
    w = W.partitionBy("user_id").orderBy("event_id").rowsBetween(0, W.unboundedFollowing)
    return _t(s, d, "events").select("event_id", F.max("value").over(w).alias("m"))


# ---- order, limits, sets


@op("SELECT p_partkey, row_number() OVER (ORDER BY p_retailprice DESC, p_size, p_partkey) AS pos FROM part")
def op_sort_multi(s, d):
    return _t(s, d, "part").select("p_partkey", F.row_number().over(W.orderBy(F.col("p_retailprice").desc(), "p_size", "p_partkey")).alias("pos"))


@op("SELECT p_partkey, p_retailprice FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 10")
def op_topk_global(s, d):
    return _t(s, d, "part").select("p_partkey", "p_retailprice").orderBy(F.col("p_retailprice").desc(), "p_partkey").limit(10)


@op("SELECT p_brand, p_partkey, rn FROM (SELECT *, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS rn FROM part) WHERE rn <= 3")
def op_topk_group(s, d):
    w = W.partitionBy("p_brand").orderBy(F.col("p_retailprice").desc(), "p_partkey")
    return _t(s, d, "part").withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("p_brand", "p_partkey", "rn")


@op("SELECT p_partkey FROM part ORDER BY p_partkey LIMIT 10 OFFSET 20")
def op_offset(s, d):
    return _t(s, d, "part").select("p_partkey").orderBy("p_partkey").offset(20).limit(10)


_A, _B = "SELECT c_nationkey AS k FROM customer", "SELECT s_nationkey AS k FROM supplier"


def _two(s, d):
    c, u = _t(s, d, "customer", "supplier")
    return c.select(F.col("c_nationkey").alias("k")), u.select(F.col("s_nationkey").alias("k"))


@op(f"{_A} UNION ALL {_B}")
def op_union_all(s, d):
    a, b = _two(s, d)
    return a.unionByName(b)


@op(f"{_A} UNION {_B}")
def op_union(s, d):
    a, b = _two(s, d)
    return a.unionByName(b).distinct()


@op(f"{_A} INTERSECT {_B}")
def op_intersect(s, d):
    a, b = _two(s, d)
    return a.intersect(b)


@op(f"{_A} EXCEPT {_B}")
def op_except(s, d):
    a, b = _two(s, d)
    return a.subtract(b)


@op(f"{_A} EXCEPT ALL {_B}")
def op_except_all(s, d):
    a, b = _two(s, d)
    return a.exceptAll(b)


# ---- subqueries and CTEs, through SQL text


def _views(s, d, *names):
    for n in names:
        table(s, d, n).createOrReplaceTempView(f"roilens_{n}")


@op("SELECT p_partkey FROM part WHERE p_retailprice > (SELECT avg(p_retailprice) FROM part)")
def op_scalar_subquery(s, d):
    _views(s, d, "part")
    return s.sql("SELECT p_partkey FROM roilens_part WHERE p_retailprice > (SELECT avg(p_retailprice) FROM roilens_part)")


@op("SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o_totalprice > 300000)")
def op_exists(s, d):
    _views(s, d, "customer", "orders")
    return s.sql("SELECT c_custkey FROM roilens_customer c WHERE EXISTS (SELECT 1 FROM roilens_orders o WHERE o.o_custkey = c.c_custkey AND o_totalprice > 300000)")


@op("SELECT p_partkey FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_quantity = 50)")
def op_in_subquery(s, d):
    _views(s, d, "part", "lineitem")
    return s.sql("SELECT p_partkey FROM roilens_part WHERE p_partkey IN (SELECT l_partkey FROM roilens_lineitem WHERE l_quantity = 50)")


@op("SELECT p_partkey FROM part p WHERE p_retailprice = (SELECT max(p_retailprice) FROM part q WHERE q.p_brand = p.p_brand)")
def op_correlated_max(s, d):
    _views(s, d, "part")
    return s.sql("SELECT p_partkey FROM roilens_part p WHERE p_retailprice = (SELECT max(p_retailprice) FROM roilens_part q WHERE q.p_brand = p.p_brand)")


@op("WITH a AS (SELECT p_brand, avg(p_retailprice) AS m FROM part GROUP BY 1) SELECT p_partkey, round(p_retailprice - m, 6) AS dev FROM part JOIN a USING (p_brand)")
def op_cte(s, d):
    _views(s, d, "part")
    return s.sql("WITH a AS (SELECT p_brand, avg(p_retailprice) AS m FROM roilens_part GROUP BY 1) SELECT p_partkey, round(p_retailprice - m, 6) AS dev FROM roilens_part JOIN a USING (p_brand)")


_RECURSIVE = "r(n, s) AS (SELECT n, c FROM {z} WHERE n = 1 UNION ALL SELECT z.n, r.s + z.c FROM r JOIN {z} z ON z.n = r.n + 1 WHERE r.n < 20) SELECT n, s FROM r"


@op("WITH RECURSIVE sizes AS MATERIALIZED (SELECT cast(l_quantity AS INT) AS n, count(*) AS c FROM lineitem GROUP BY 1), " + _RECURSIVE.format(z="sizes"))
def op_recursive_series(s, d):
    """Lines of orders by quantity, added up from 1 to 20 by recursion; the steps read the few counts, written once."""
    sizes = _t(s, d, "lineitem").groupBy(F.col("l_quantity").cast("int").alias("n")).agg(F.count("*").alias("c"))
    return s.sql("WITH RECURSIVE " + _RECURSIVE, z=written(sizes, "sizes"))


# ---- samples and distinct rows


@op("SELECT event_id FROM events WHERE (event_id * 2654435761) % 4294967296 < 429496730")
def op_sample_hash(s, d):
    return _t(s, d, "events").where("(event_id * 2654435761L) % 4294967296L < 429496730L").select("event_id")


@op("SELECT DISTINCT p_brand, p_type FROM part")
def op_distinct(s, d):
    return _t(s, d, "part").select("p_brand", "p_type").distinct()


@op("SELECT p_brand, min(p_partkey) AS p_partkey FROM part GROUP BY p_brand")
def op_drop_duplicates(s, d):
    w = W.partitionBy("p_brand").orderBy("p_partkey")
    return _t(s, d, "part").withColumn("r", F.row_number().over(w)).where("r = 1").select("p_brand", "p_partkey")


# ---- scalars


@op("SELECT p_partkey, round(cos(radians(p_size)), 6) AS c, round(sqrt(p_retailprice), 6) AS r, round(exp(-p_size / 10.0), 6) AS e, greatest(p_size, 25) AS g, p_partkey & 15 AS b, round(atan2(p_size::DOUBLE, 7), 6) AS t FROM part")
def op_math(s, d):
    return _t(s, d, "part").select(
        "p_partkey", F.round(F.cos(F.radians("p_size")), 6).alias("c"), F.round(F.sqrt("p_retailprice"), 6).alias("r"), F.round(F.exp(-F.col("p_size") / 10.0), 6).alias("e"),
        F.greatest("p_size", F.lit(25)).alias("g"), F.col("p_partkey").bitwiseAND(15).alias("b"), F.round(F.atan2(F.col("p_size").cast("double"), F.lit(7.0)), 6).alias("t"),
    )


@op("SELECT p_partkey, split_part(p_name, ' ', 1) AS c, lower(p_brand) AS l, substring(p_type, 1, 3) AS s3, length(p_name) AS n, concat_ws('/', p_brand, p_type) AS j FROM part")
def op_string(s, d):
    return _t(s, d, "part").select("p_partkey", F.split_part("p_name", F.lit(" "), F.lit(1)).alias("c"), F.lower("p_brand").alias("l"), F.substring("p_type", 1, 3).alias("s3"), F.length("p_name").alias("n"), F.concat_ws("/", "p_brand", "p_type").alias("j"))


@op("SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, date_diff('day', DATE '1992-01-01', o_orderdate::DATE) AS n, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS f FROM orders")
def op_date(s, d):
    return _t(s, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.expr("datediff(cast(o_orderdate as date), date'1992-01-01')").alias("n"), F.date_format(F.trunc(F.col("o_orderdate").cast("date"), "month"), "yyyy-MM-dd").alias("f"))


@op("SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 6) AS ss, len(list_filter(embedding, lambda x: x > 0)) AS pos FROM embeddings")
def op_array_hof(s, d):
    sq = F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda a, x: a + x)
    return _t(s, d, "embeddings").select("vec_id", F.round(sq, 6).alias("ss"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("pos"))


@op("SELECT p_partkey, 'brand=' || p_brand || ';type=' || p_type AS m FROM part")
def op_map(s, d):
    m = F.create_map(F.lit("brand"), F.col("p_brand"), F.lit("type"), F.col("p_type"))
    e = F.transform(F.array_sort(F.map_entries(m)), lambda x: F.concat(x["key"], F.lit("="), x["value"]))
    return _t(s, d, "part").select("p_partkey", F.array_join(e, ";").alias("m"))


@op("SELECT event_id, (props->>'$.k')::INT AS k FROM events")
def op_json(s, d):
    return _t(s, d, "events").select("event_id", F.from_json("props", "k int").getField("k").alias("k"))


@op("SELECT event_id, CASE WHEN value >= 120 THEN 'noise' WHEN value >= 60 THEN 'far' ELSE 'near' END AS band, nullif(event_type, 'view') AS t FROM events")
def op_conditional(s, d):
    band = F.when(F.col("value") >= 120, "noise").when(F.col("value") >= 60, "far").otherwise("near")
    return _t(s, d, "events").select("event_id", band.alias("band"), F.nullif(F.col("event_type"), F.lit("view")).alias("t"))


@op("SELECT a.vec_id, round(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda x: x[1]::DOUBLE * x[2]::DOUBLE)) / sqrt(list_sum(list_transform(a.embedding, lambda x: x::DOUBLE * x::DOUBLE))) / sqrt(list_sum(list_transform(b.embedding, lambda x: x::DOUBLE * x::DOUBLE))), 5) AS c FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def op_cosine_dense(s, d):
    from ..suggest.relevance import dense_cosine

    e = _t(s, d, "embeddings")
    b = e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("b"))
    return e.join(b, "vec_id").select("vec_id", F.round(dense_cosine(F.col("embedding"), F.col("b")), 5).alias("c"))


@op("SELECT page_id, split_part(split_part(url, '//', 2), '/', 1) AS host, length(html) AS n FROM pages")
def op_url(s, d):
    return _t(s, d, "pages").select("page_id", F.split_part(F.split_part("url", F.lit("//"), F.lit(2)), F.lit("/"), F.lit(1)).alias("host"), F.length("html").alias("n"))


@op("SELECT doc_id, regexp_extract(text, '([A-Za-z]+)', 1) AS w, length(regexp_replace(text, '[^0-9]', '', 'g')) AS digits FROM documents")
def op_regex(s, d):
    return _t(s, d, "documents").select("doc_id", F.regexp_extract("text", "([A-Za-z]+)", 1).alias("w"), F.length(F.regexp_replace("text", "[^0-9]", "")).alias("digits"))


# ---- user-defined functions


@op("SELECT p_partkey, round(sqrt((p_size * p_size + 9)::DOUBLE), 6) AS h FROM part")
def op_udf_arrow(s, d):
    @F.pandas_udf("double")
    def hyp(x: pd.Series) -> pd.Series:
        return ((x * x + 9) ** 0.5).round(6)

    return _t(s, d, "part").select("p_partkey", hyp("p_size").alias("h"))


@op()
def op_udaf_hull(s, d):
    from ..mine import hull

    p = _t(s, d, "part").select(F.lit(0).cast("long").alias("session_id"), F.lit(1).alias("seg"), (F.col("p_partkey") % 8).alias("cluster_id"), F.expr("(p_partkey * 48271) % 1601 - 800").alias("x"), F.expr("(p_partkey * 16807) % 901 - 450").alias("y"), F.col("p_partkey").alias("event_id"))
    return hull.convex_hull(p).select("cluster_id", F.size("poly").alias("vertices"), F.round("area", 6).alias("area"))


@op("SELECT b.p_brand, i.i AS edge, (p_n * 7 + i.i) % 100 AS v FROM (SELECT p_brand, count(*) AS p_n FROM part GROUP BY 1) b, generate_series(0, 3) i(i)")
def op_udtf_edges(s, d):
    @F.udtf(returnType="edge bigint, v bigint")
    class Edges:
        def eval(self, n: int):
            for i in range(4):
                yield i, (n * 7 + i) % 100

    s.udtf.register("roilens_edges", Edges)
    _t(s, d, "part").groupBy("p_brand").agg(F.count("*").alias("n")).createOrReplaceTempView("roilens_brands")
    return s.sql("SELECT p_brand, e.edge, e.v FROM roilens_brands, LATERAL roilens_edges(n) e")


@op("SELECT p_brand, round(avg(p_retailprice), 3) AS m FROM part GROUP BY 1")
def op_grouped_map(s, d):
    def mean(f: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"p_brand": [f.p_brand.iloc[0]], "m": [round(float(f.p_retailprice.mean()), 3)]})

    return _t(s, d, "part").select("p_brand", "p_retailprice").groupBy("p_brand").applyInPandas(mean, "p_brand string, m double")


@op("SELECT coalesce(a.k, b.k) AS k, coalesce(a.n, 0) AS c, coalesce(b.n, 0) AS s FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer GROUP BY 1) a FULL JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier GROUP BY 1) b ON a.k = b.k")
def op_cogroup(s, d):
    a, b = _two(s, d)

    def both(x: pd.DataFrame, y: pd.DataFrame) -> pd.DataFrame:
        k = (x if len(x) else y).k.iloc[0]
        return pd.DataFrame({"k": [k], "c": [len(x)], "s": [len(y)]})

    return a.groupBy("k").cogroup(b.groupBy("k")).applyInPandas(both, "k int, c long, s long")


# ---- reading back what was written


def _scratch(s: SparkSession, name: str) -> str:
    import uuid

    return f"{shared_dir(s).rstrip('/')}/{name}-{uuid.uuid4().hex}"


_PART = "SELECT p_partkey, p_name, p_size FROM part"


def _part(s, d):
    return _t(s, d, "part").select("p_partkey", "p_name", "p_size")


@op(_PART)
def op_parquet_roundtrip(s, d):
    path = _scratch(s, "parquet")
    _part(s, d).write.parquet(path)
    return s.read.parquet(path)


@op(_PART)
def op_json_roundtrip(s, d):
    path = _scratch(s, "json")
    _part(s, d).write.json(path)
    return s.read.schema("p_partkey long, p_name string, p_size int").json(path)


@op(_PART)
def op_csv_roundtrip(s, d):
    path = _scratch(s, "csv")
    _part(s, d).write.option("header", True).csv(path)
    return s.read.schema("p_partkey long, p_name string, p_size int").option("header", True).csv(path)


@op("SELECT p_partkey, p_size FROM part WHERE p_size = 7")
def op_partitioned_write_pruned(s, d):
    path = _scratch(s, "parted")
    _part(s, d).select("p_partkey", "p_size").repartition("p_size").write.partitionBy("p_size").parquet(path)
    return s.read.parquet(path).where("p_size = 7").select("p_partkey", F.col("p_size").cast("int").alias("p_size"))
