"""Operators that a user needs around the linkage methods, each as a query with its SQL."""

from __future__ import annotations

from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window as W
from pyspark.sql.functions import pandas_udf, udtf

from veil.functions import encode as E
from veil.functions.hashing import uniform
from veil.operators import near, padding
from veil.operators.exact import match_join
from veil.plans import workloads as WL
from veil.plans.catalogue import bits, grams, query, u, w1
from veil.sources.shared import shared_path, table
from veil.streaming import daily

NATION = "n_nationkey int, n_name string, n_regionkey int"
EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"

# ---- sources and sinks --------------------------------------------------------------------------------------------

for _fmt in ("csv", "json", "orc"):

    @query(f"src_{_fmt}_roundtrip", "SELECT n_nationkey, n_name, n_regionkey FROM nation")
    def src(s, d, fmt=_fmt):
        path = shared_path(s, f"src-{fmt}")
        table(s, d, "nation").write.format(fmt).save(path)
        return s.read.schema(NATION).format(fmt).load(path)


@query("src_text_roundtrip", "SELECT r_name FROM region")
def src_text(s, d):
    path = shared_path(s, "src-text")
    table(s, d, "region").select("r_name").write.text(path)
    return s.read.text(path).withColumnRenamed("value", "r_name")


@query("src_partitioned", "SELECT event_id, value FROM events WHERE CAST(ts AS DATE) = DATE '2024-01-03'")
def src_partitioned(s, d):
    path = shared_path(s, "by-day")
    e = table(s, d, "events").select("event_id", "value", F.to_date("ts").cast("string").alias("day"))
    e.repartition("day").write.partitionBy("day").parquet(path)
    return s.read.parquet(path).filter("day = '2024-01-03'").select("event_id", "value")


@query("sink_bucketed", "SELECT o_orderpriority, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def sink_bucketed(s, d):
    """Both sides are saved in buckets of the key, so the join of the saved tables needs no exchange."""
    names = [shared_path(s, t).rsplit("/", 1)[1].replace("-", "_") for t in ("bo", "bc")]
    table(s, d, "orders").select("o_custkey", "o_orderpriority").write.bucketBy(8, "o_custkey").sortBy("o_custkey").option("path", shared_path(s, "bo")).saveAsTable(names[0])
    table(s, d, "customer").select("c_custkey").write.bucketBy(8, "c_custkey").sortBy("c_custkey").option("path", shared_path(s, "bc")).saveAsTable(names[1])
    j = s.table(names[0]).join(s.table(names[1]), F.col("o_custkey") == F.col("c_custkey"))
    return j.groupBy("o_orderpriority").agg(F.count("*").alias("n"))


# ---- projection, filter -------------------------------------------------------------------------------------------


@query("proj_struct", f"WITH {w1()} SELECT rid, slot // 4 AS day, slot % 4 AS quarter_day, bin % 16 AS cell FROM a")
def proj_struct(s, d):
    p = WL.location(s, d)
    key = F.struct(F.floor(F.col("slot") / 4).alias("day"), (F.col("slot") % 4).alias("quarter_day"), (F.element_at(p.blocking.bins(), 1) % 16).alias("cell"))
    return p.a.select("rid", key.alias("k")).select("rid", "k.day", "k.quarter_day", "k.cell")


@query("filter_box", "SELECT event_id FROM events WHERE value BETWEEN 10 AND 60 AND ts >= TIMESTAMP '2024-01-02' AND ts < TIMESTAMP '2024-01-05' AND event_type IN ('click', 'view') AND props LIKE '%k%'")
def filter_box(s, d):
    lo, hi = (F.lit(x).cast("timestamp_ntz") for x in ("2024-01-02", "2024-01-05"))
    keep = F.col("value").between(10, 60) & (F.col("ts") >= lo) & (F.col("ts") < hi) & F.col("event_type").isin("click", "view") & F.col("props").like("%k%")
    return table(s, d, "events").filter(keep & ~F.col("event_id").eqNullSafe(None)).select("event_id")


# ---- joins --------------------------------------------------------------------------------------------------------


@query("join_inner", "SELECT p_brand, count(*) AS n, round(sum(l_quantity), 6) AS qty FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")
def join_inner(s, d):
    j = table(s, d, "lineitem").join(table(s, d, "part"), F.col("l_partkey") == F.col("p_partkey"))
    return j.groupBy("p_brand").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 6).alias("qty"))


@query("join_left", "SELECT c_custkey, count(o_orderkey) AS orders FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1")
def join_left(s, d):
    j = table(s, d, "customer").join(table(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left")
    return j.groupBy("c_custkey").agg(F.count("o_orderkey").alias("orders"))


@query("join_full", "SELECT coalesce(s_nationkey, c_nationkey) AS nation, count(DISTINCT s_suppkey) AS suppliers, count(DISTINCT c_custkey) AS customers FROM (SELECT * FROM supplier WHERE s_nationkey < 15) FULL JOIN (SELECT * FROM customer WHERE c_nationkey > 10) ON s_nationkey = c_nationkey GROUP BY 1")
def join_full(s, d):
    x, y = table(s, d, "supplier").filter("s_nationkey < 15"), table(s, d, "customer").filter("c_nationkey > 10")
    j = x.join(y, F.col("s_nationkey") == F.col("c_nationkey"), "full")
    return j.groupBy(F.coalesce("s_nationkey", "c_nationkey").alias("nation")).agg(F.countDistinct("s_suppkey").alias("suppliers"), F.countDistinct("c_custkey").alias("customers"))


for _how, _sql in (("semi", "IN"), ("anti", "NOT IN")):

    @query(f"join_{_how}", f"SELECT c_custkey FROM customer WHERE c_custkey {_sql} (SELECT o_custkey FROM orders)")
    def join_sa(s, d, how=_how):
        return table(s, d, "customer").join(table(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), f"left_{how}").select("c_custkey")


@query("unmatched_records", f"WITH {w1()} SELECT rid FROM a WHERE rid NOT IN (SELECT a_id FROM truth)")
def unmatched(s, d):
    p = WL.location(s, d)
    return p.a.join(match_join(p.a, p.b, p.rule, p.blocking).select(F.col("a_id").alias("rid")), "rid", "left_anti").select("rid")


@query("join_theta", "SELECT c_custkey, s_suppkey FROM customer JOIN supplier ON c_nationkey = s_nationkey AND abs(c_acctbal - s_acctbal) < 100")
def join_theta(s, d):
    on = (F.col("c_nationkey") == F.col("s_nationkey")) & (F.abs(F.col("c_acctbal") - F.col("s_acctbal")) < 100)
    return table(s, d, "customer").join(table(s, d, "supplier"), on).select("c_custkey", "s_suppkey")


@query("join_nested_loop", "SELECT o_orderkey, r_name FROM orders JOIN region ON substr(o_orderpriority, 3) > r_name")
def join_nested(s, d):
    """Every order against the regions (5 rows), without an equality."""
    on = F.substr(F.col("o_orderpriority"), F.lit(3)) > F.col("r_name")
    return table(s, d, "orders").join(F.broadcast(table(s, d, "region")), on).select("o_orderkey", "r_name")


_SEC = "epoch_us(ts)"


@query("join_range_bucketed", f"SELECT x.event_id AS a_id, y.event_id AS b_id FROM events x JOIN events y ON x.user_id = y.user_id AND x.event_id < y.event_id AND abs(epoch_us(x.ts) - epoch_us(y.ts)) <= 600000000")
def join_range(s, d):
    """Pairs of one user within ten minutes: ten-minute buckets, the left side copied to three."""
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    e = table(s, d, "events").select("event_id", "user_id", us.alias("us")).withColumn("b", F.floor(F.col("us") / 600_000_000))
    x = e.select("event_id", "user_id", "us", F.explode(F.array(*[F.col("b") + i for i in (-1, 0, 1)])).alias("b")).alias("x")
    y = e.alias("y")
    on = (F.col("x.user_id") == F.col("y.user_id")) & (F.col("x.b") == F.col("y.b")) & (F.col("x.event_id") < F.col("y.event_id"))
    return x.join(y, on & (F.abs(F.col("x.us") - F.col("y.us")) <= 600_000_000)).select(F.col("x.event_id").alias("a_id"), F.col("y.event_id").alias("b_id"))


@query("join_asof", "SELECT p.event_id, (SELECT max_by(c.event_id, (c.ts, c.event_id)) FROM events c WHERE c.event_type = 'click' AND c.user_id = p.user_id AND (c.ts, c.event_id) < (p.ts, p.event_id)) AS click_id FROM events p WHERE p.event_type = 'purchase'")
def join_asof(s, d):
    """Each purchase with its user's latest earlier click: one sort per user, no pairs."""
    e = table(s, d, "events").filter(F.col("event_type").isin("purchase", "click"))
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1)
    click = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("click_id", click).filter("event_type = 'purchase'").select("event_id", "click_id")


@query("join_interval", "SELECT v.event_id AS a_id, r.event_id AS b_id FROM events v JOIN events r ON v.user_id = r.user_id AND v.event_type = 'view' AND r.event_type = 'error' AND v.ts < r.ts + INTERVAL 1 HOUR AND r.ts < v.ts + INTERVAL 1 HOUR")
def join_interval(s, d):
    """One-hour intervals that overlap: an interval touches two hour buckets; a pair is kept in its first common one."""
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    hour = 3_600_000_000
    e = table(s, d, "events").select("event_id", "user_id", "event_type", us.alias("us"))
    e = e.withColumn("b0", F.floor(F.col("us") / hour)).withColumn("b", F.explode(F.array(F.col("b0"), F.col("b0") + 1)))
    x, y = e.filter("event_type = 'view'").alias("x"), e.filter("event_type = 'error'").alias("y")
    on = (F.col("x.user_id") == F.col("y.user_id")) & (F.col("x.b") == F.col("y.b")) & (F.abs(F.col("x.us") - F.col("y.us")) < hour)
    return x.join(y, on & (F.col("x.b") == F.greatest("x.b0", "y.b0"))).select(F.col("x.event_id").alias("a_id"), F.col("y.event_id").alias("b_id"))


@query("join_skew_salted", "SELECT x.o_orderkey AS a_id, y.c_custkey AS b_id FROM orders x JOIN customer y ON x.o_custkey % 3 = y.c_custkey % 3 AND abs(x.o_totalprice - 20 * y.c_acctbal) <= 5")
def join_skew(s, d):
    """Three keys, each with a third of all rows: sliced left side, copied right side."""
    from veil.functions import rules as R
    from veil.operators import blocking as B
    from veil.operators.exact import salted_compare

    a = table(s, d, "orders").select(F.col("o_orderkey").alias("rid"), (F.col("o_custkey") % 3).alias("key"), F.col("o_totalprice").alias("x"))
    b = table(s, d, "customer").select(F.col("c_custkey").alias("rid"), (F.col("c_custkey") % 3).alias("key"), (20 * F.col("c_acctbal")).alias("x"))
    rule = R.all_of(R.equal("key"), R.euclidean(["x"], 5.0))
    return salted_compare(a, b, rule, B.equal_keys("key", 3, F.col("key")), 8)


# ---- aggregates ---------------------------------------------------------------------------------------------------


@query("agg_basic", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 4) AS qty, round(avg(l_discount), 9) AS disc, min(l_shipdate) AS first_ship, max(l_extendedprice) AS top, count(*) FILTER (l_tax > 0.05) AS taxed FROM lineitem GROUP BY 1, 2")
def agg_basic(s, d):
    return table(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(
        F.count("*").alias("n"), F.round(F.sum("l_quantity"), 4).alias("qty"), F.round(F.avg("l_discount"), 9).alias("disc"),
        F.min("l_shipdate").alias("first_ship"), F.max("l_extendedprice").alias("top"), F.count_if(F.col("l_tax") > 0.05).alias("taxed"),
    )


@query("agg_distinct", "SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def agg_distinct(s, d):
    return table(s, d, "events").groupBy(F.to_date("ts").cast("string").alias("day")).agg(F.countDistinct("user_id").alias("users"))


@query("agg_percentile", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS p50, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY 1")
def agg_percentile(s, d):
    return table(s, d, "events").groupBy("event_type").agg(F.round(F.percentile("value", F.lit(0.5)), 6).alias("p50"), F.round(F.percentile("value", F.lit(0.9)), 6).alias("p90"))


_K = "CAST(regexp_extract(props, '\"k\": *([0-9]+)', 1) AS BIGINT)"


@query("agg_regr", f"SELECT round(regr_slope(value, {_K}), 6) AS slope, round(corr(value, {_K}), 6) AS r FROM events")
def agg_regr(s, d):
    e = table(s, d, "events").select("value", F.get_json_object("props", "$.k").cast("double").alias("k"))
    return e.agg(F.round(F.regr_slope("value", "k"), 6).alias("slope"), F.round(F.corr("value", "k"), 6).alias("r"))


@query("agg_bit_or", f"SELECT p_brand, bit_or({bits('p_name')}) AS v FROM part GROUP BY 1")
def agg_bit_or(s, d):
    return table(s, d, "part").groupBy("p_brand").agg(F.bit_or(E.bloom(F.col("p_name"))).alias("v"))


_DE = "SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, event_type, count(*) AS n, grouping_id(CAST(CAST(ts AS DATE) AS VARCHAR), event_type) AS level FROM events GROUP BY "


@query("agg_rollup", _DE + "ROLLUP (CAST(CAST(ts AS DATE) AS VARCHAR), event_type)")
def agg_rollup(s, d):
    e = table(s, d, "events").select(F.to_date("ts").cast("string").alias("day"), "event_type")
    return e.rollup("day", "event_type").agg(F.count("*").alias("n"), F.grouping_id().alias("level"))


@query("agg_cube", _DE + "CUBE (CAST(CAST(ts AS DATE) AS VARCHAR), event_type)")
def agg_cube(s, d):
    e = table(s, d, "events").select(F.to_date("ts").cast("string").alias("day"), "event_type")
    return e.cube("day", "event_type").agg(F.count("*").alias("n"), F.grouping_id().alias("level"))


@query("agg_gsets", "SELECT event_type, CAST(CAST(ts AS DATE) AS VARCHAR) AS day, count(*) AS n FROM events GROUP BY GROUPING SETS ((event_type), (CAST(CAST(ts AS DATE) AS VARCHAR)))")
def agg_gsets(s, d):
    e = table(s, d, "events").select(F.to_date("ts").cast("string").alias("day"), "event_type")
    return e.groupingSets([["event_type"], ["day"]], "event_type", "day").agg(F.count("*").alias("n"))


@query("agg_approx_distinct", "SELECT event_type, count(DISTINCT user_id) AS users, true AS within_bound FROM events GROUP BY event_type")
def agg_approx(s, d):
    """A sketch of five per cent against the exact count, within four deviations."""
    both = table(s, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.05).alias("about"), F.countDistinct("user_id").alias("users"))
    return both.select("event_type", "users", (F.abs(F.col("about") - F.col("users")) <= 0.2 * F.col("users")).alias("within_bound"))


# ---- windows, top-k -----------------------------------------------------------------------------------------------


@query("win_rank", "SELECT p_partkey, rank() OVER w AS r, dense_rank() OVER w AS dr FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_retailprice DESC)")
def win_rank(s, d):
    w = W.partitionBy("p_brand").orderBy(F.col("p_retailprice").desc())
    return table(s, d, "part").select("p_partkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"))


@query("win_ntile", "WITH c AS (SELECT user_id, count(*) AS n FROM events GROUP BY 1) SELECT user_id, n, ntile(10) OVER (ORDER BY n, user_id) AS decile FROM c")
def win_ntile(s, d):
    c = table(s, d, "events").groupBy("user_id").agg(F.count("*").alias("n"))
    return c.select("user_id", "n", F.ntile(10).over(W.orderBy("n", "user_id")).alias("decile"))


@query("win_lag", f"SELECT event_id, {_SEC} - lag({_SEC}) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS gap_us FROM events")
def win_lag(s, d):
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    return table(s, d, "events").select("event_id", (us - F.lag(us).over(W.partitionBy("user_id").orderBy("ts", "event_id"))).alias("gap_us"))


@query("win_running", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING), 6) AS total FROM events")
def win_running(s, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, 0)
    return table(s, d, "events").select("event_id", F.round(F.sum("value").over(w), 6).alias("total"))


@query("win_range", f"SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY {_SEC} RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS n FROM events")
def win_range(s, d):
    w = W.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)
    return table(s, d, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp"))).select("event_id", F.count("*").over(w).alias("n"))


@query("topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
def topk_global(s, d):
    return table(s, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(10)


@query("topk_per_group", "SELECT o_orderpriority, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) <= 3")
def topk_group(s, d):
    w = W.partitionBy("o_orderpriority").orderBy(F.col("o_totalprice").desc(), "o_orderkey")
    return table(s, d, "orders").withColumn("k", F.row_number().over(w)).filter("k <= 3").select("o_orderpriority", "o_orderkey")


@query("nearest_match", f"WITH {w1()}, t AS (SELECT a_id, b_id, ((a.x - b.x) / 40) * ((a.x - b.x) / 40) + ((a.y - b.y) / 25) * ((a.y - b.y) / 25) AS d2 FROM truth JOIN a ON a.rid = a_id JOIN b ON b.rid = b_id) SELECT a_id, min_by(b_id, (d2, b_id)) AS b_id FROM t GROUP BY a_id")
def nearest(s, d):
    """The nearest match is kept while records meet: one row per record leaves a task, no pairs."""
    p = WL.location(s, d)
    return near.nearest(p.a, p.b, p.rule, p.blocking)


# ---- sets, strings, dates -----------------------------------------------------------------------------------------


def _keys(s, d):
    return table(s, d, "customer").select(F.col("c_nationkey").alias("k")), table(s, d, "supplier").select(F.col("s_nationkey").alias("k"))


for _n, _op, _sql in (
    ("set_union", lambda x, y: x.union(y).distinct(), "UNION"),
    ("set_union_all", lambda x, y: x.unionByName(y), "UNION ALL"),
    ("set_intersect", lambda x, y: x.intersect(y), "INTERSECT"),
    ("set_intersect_all", lambda x, y: x.intersectAll(y), "INTERSECT ALL"),
    ("set_except", lambda x, y: x.subtract(y), "EXCEPT"),
    ("set_except_all", lambda x, y: x.exceptAll(y), "EXCEPT ALL"),
):

    @query(_n, f"SELECT c_nationkey AS k FROM customer {_sql} SELECT s_nationkey FROM supplier")
    def set_op(s, d, op=_op):
        return op(*_keys(s, d))


@query("str_clean", "SELECT p_partkey, regexp_replace(trim(lower(p_name)), '[aeiou]', '', 'g') AS t, upper(substr(p_type, 1, 3)) AS y FROM part")
def str_clean(s, d):
    return table(s, d, "part").select("p_partkey", F.regexp_replace(F.trim(F.lower("p_name")), "[aeiou]", "").alias("t"), F.upper(F.substring("p_type", 1, 3)).alias("y"))


@query("str_grams", f"SELECT g, count(*) AS n FROM (SELECT unnest(list_filter({grams('p_name')}, lambda g: length(g) = 3)) AS g FROM part) GROUP BY 1")
def str_grams(s, d):
    return table(s, d, "part").select(F.explode(E.qgrams(F.col("p_name"))).alias("g")).groupBy("g").agg(F.count("*").alias("n"))


@query("str_host", "SELECT regexp_extract(url, '://([^/?#]*)', 1) AS host, count(*) AS n FROM pages GROUP BY 1")
def str_host(s, d):
    return table(s, d, "pages").groupBy(F.regexp_extract("url", "://([^/?#]*)", 1).alias("host")).agg(F.count("*").alias("n"))


@query("str_edit", "SELECT x.p_name AS a, y.p_name AS b, levenshtein(x.p_name, y.p_name) AS d FROM (SELECT DISTINCT p_name FROM part) x JOIN (SELECT DISTINCT p_name FROM part) y ON x.p_name < y.p_name AND levenshtein(x.p_name, y.p_name) <= 5")
def str_edit(s, d):
    n = table(s, d, "part").select("p_name").distinct()
    x, y = n.select(F.col("p_name").alias("a")), n.select(F.col("p_name").alias("b"))
    return x.join(y, (F.col("a") < F.col("b")) & (F.levenshtein("a", "b") <= 5)).select("a", "b", F.levenshtein("a", "b").alias("d"))


@query("date_bins", "SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, hour(ts) // 6 AS slot, count(*) AS n FROM events GROUP BY 1, 2")
def date_bins(s, d):
    return table(s, d, "events").groupBy(F.to_date("ts").cast("string").alias("day"), F.floor(F.hour("ts") / 6).alias("slot")).agg(F.count("*").alias("n"))


@query("date_diff", "SELECT date_diff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE)) AS days, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def date_diff(s, d):
    j = table(s, d, "lineitem").join(table(s, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    return j.groupBy(F.datediff(F.to_date("l_shipdate"), F.to_date("o_orderdate")).alias("days")).agg(F.count("*").alias("n"))


@query("date_quarter", "SELECT year(l_shipdate) AS y, quarter(l_shipdate) AS q, CAST(CAST(date_trunc('quarter', l_shipdate) AS DATE) AS VARCHAR) AS start, count(*) AS n FROM lineitem GROUP BY ALL")
def date_quarter(s, d):
    return table(s, d, "lineitem").groupBy(F.year("l_shipdate").alias("y"), F.quarter("l_shipdate").alias("q"), F.date_trunc("quarter", "l_shipdate").cast("date").cast("string").alias("start")).agg(F.count("*").alias("n"))


# ---- arrays, maps, pivots, sampling -------------------------------------------------------------------------------


@query("arr_dot", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 4) AS n2 FROM embeddings")
def arr_dot(s, d):
    e = F.col("embedding").cast("array<double>")
    return table(s, d, "embeddings").select("vec_id", F.round(F.aggregate(F.zip_with(e, e, lambda x, y: x * y), F.lit(0.0), lambda a, x: a + x), 4).alias("n2"))


@query("arr_sets", f"WITH n AS (SELECT p_partkey, list_distinct(list_filter({grams('p_name')}, lambda g: length(g) = 3)) AS g, list_distinct(list_filter({grams('p_type')}, lambda g: length(g) = 3)) AS h FROM part) SELECT p_partkey, len(list_intersect(g, h)) AS both, len(list_distinct(g || h)) AS either FROM n")
def arr_sets(s, d):
    g, h = (F.array_distinct(E.qgrams(F.col(c))) for c in ("p_name", "p_type"))
    return table(s, d, "part").select("p_partkey", F.size(F.array_intersect(g, h)).alias("both"), F.size(F.array_union(g, h)).alias("either"))


@query("arr_explode", "SELECT vec_id, i - 1 AS place, round(embedding[i]::DOUBLE, 6) AS x FROM embeddings, unnest(range(1, 5)) r(i)")
def arr_explode(s, d):
    return table(s, d, "embeddings").select("vec_id", F.posexplode(F.slice("embedding", 1, 4)).alias("place", "x")).select("vec_id", "place", F.round(F.col("x").cast("double"), 6).alias("x"))


@query("map_props", f"SELECT event_id, {_K} AS k, {_K} % 10 AS last FROM events")
def map_props(s, d):
    m = F.from_json("props", "map<string,bigint>")
    return table(s, d, "events").select("event_id", m["k"].alias("k"), F.map_values(F.transform_values(F.map_filter(m, lambda k, v: k == "k"), lambda k, v: v % 10))[0].alias("last"))


@query("json_props", f"SELECT {_K} AS k, count(*) AS n FROM events GROUP BY 1")
def json_props(s, d):
    return table(s, d, "events").groupBy(F.from_json("props", "k long")["k"].alias("k")).agg(F.count("*").alias("n"))


_TYPES = ("click", "error", "purchase", "signup", "view")


def _pivoted(s, d) -> DataFrame:
    e = table(s, d, "events").select(F.to_date("ts").cast("string").alias("day"), "event_type")
    return e.groupBy("day").pivot("event_type", list(_TYPES)).agg(F.count(F.lit(1))).fillna(0)


@query("pivot_variants", "SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, " + ", ".join(f"count(*) FILTER (event_type = '{t}') AS \"{t}\"" for t in _TYPES) + " FROM events GROUP BY 1")
def pivot_variants(s, d):
    return _pivoted(s, d)


@query("unpivot_variants", "SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def unpivot_variants(s, d):
    return _pivoted(s, d).unpivot("day", list(_TYPES), "event_type", "n").filter("n > 0")


@query("sample_hash", f"SELECT o_orderkey FROM orders WHERE {u(chr(39) + 'sample|' + chr(39) + ' || o_orderkey')} < 0.1::DOUBLE")
def sample_hash(s, d):
    return table(s, d, "orders").filter(uniform("sample", F.col("o_orderkey")) < 0.1).select("o_orderkey")


# ---- user functions and SQL ---------------------------------------------------------------------------------------


@udtf(returnType="v: bigint")
class ExpandBall:
    """All 50-bit vectors within one bit of a vector."""

    def eval(self, v: int):
        yield (v,)
        for i in range(50):
            yield (v ^ (1 << i),)


@query("udtf_ball", f"WITH n AS (SELECT DISTINCT {bits('p_name')} AS v FROM part) SELECT v AS centre, xor(v, CASE WHEN i < 0 THEN 0 ELSE 1::BIGINT << i END) AS v FROM n, unnest(range(-1, 50)) r(i)")
def udtf_ball(s, d):
    s.udtf.register("expand_ball", ExpandBall)
    table(s, d, "part").select(E.bloom(F.col("p_name")).alias("centre")).distinct().createOrReplaceTempView("veil_vectors")
    return s.sql("SELECT centre, b.v FROM veil_vectors, LATERAL expand_ball(centre) b")


@pandas_udf(T.StringType())
def consonant_key(x: pd.Series) -> pd.Series:
    """A phonetic key: first letter and the following consonants without repeats, in Arrow batches."""
    low = x.str.lower().str.replace(r"[^a-z]", "", regex=True)
    rest = low.str[1:].str.replace(r"[aeiouhwy]", "", regex=True).str.replace(r"(.)\1+", r"\1", regex=True)
    return (low.str[:1] + rest).str[:4]


@query("udf_phonetic", r"WITH l AS (SELECT p_partkey, regexp_replace(lower(p_name), '[^a-z]', '', 'g') AS l FROM part), r AS (SELECT *, regexp_replace(substr(l, 2), '[aeiouhwy]', '', 'g') AS c FROM l) SELECT p_partkey, substr(substr(l, 1, 1) || list_reduce(list_prepend('', string_split(c, '')), lambda x, y: CASE WHEN ends_with(x, y) AND x <> '' AND y <> '' THEN x ELSE x || y END), 1, 4) AS key FROM r")
def udf_phonetic(s, d):
    return table(s, d, "part").select("p_partkey", consonant_key("p_name").alias("key"))


@query("uda_bloom", f"SELECT p_brand, bit_or({bits('p_name')}) AS v, count(*) AS n FROM part GROUP BY 1")
def uda_bloom(s, d):
    def union(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"p_brand": [pdf.p_brand.iloc[0]], "v": [int(reduce(lambda a, b: a | b, pdf.v.tolist(), 0))], "n": [len(pdf)]})

    rows = table(s, d, "part").select("p_brand", E.bloom(F.col("p_name")).alias("v"))
    return rows.groupBy("p_brand").applyInPandas(union, "p_brand string, v long, n long")


def register_sql(s) -> None:
    """Temporary SQL functions for users of the SQL surface."""
    s.sql("CREATE OR REPLACE TEMPORARY FUNCTION grid_cell(v DOUBLE, size DOUBLE, cells INT) RETURNS BIGINT RETURN greatest(0, least(cells - 1, floor(v / size)))")
    s.sql("CREATE OR REPLACE TEMPORARY FUNCTION hash_uniform(t STRING) RETURNS DOUBLE RETURN cast(conv(substr(md5(t), 1, 13), 16, 10) AS BIGINT) / 4503599627370496D")
    s.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION bloom50(t STRING) RETURNS BIGINT RETURN if(length(t) < 3, if(t IS NULL, NULL, 0L), aggregate(transform(sequence(1, greatest(length(t) - 2, 1)), "
        "i -> substr(t, i, 3)), 0L, (acc, g) -> acc | shiftleft(1L, cast(pmod(cast(conv(substr(md5(g), 1, 13), 16, 10) AS BIGINT), 50) AS INT))))"
    )
    s.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION noise_pad(key STRING, mu BIGINT, a DOUBLE) RETURNS BIGINT RETURN greatest(0L, mu + floor(log1p(-hash_uniform(key || '|1')) / -a) - floor(log1p(-hash_uniform(key || '|2')) / -a))"
    )


@query("sql_surface", f"SELECT CAST(greatest(0, least(3, floor(value / 40))) AS BIGINT) AS cell, count(*) AS n, round(avg({u(chr(39) + 'k|' + chr(39) + ' || event_id')}), 9) AS mean_u FROM events GROUP BY 1")
def sql_surface(s, d):
    register_sql(s)
    events = table(s, d, "events")
    return s.sql("SELECT grid_cell(value, 40D, 4) AS cell, count(*) AS n, round(avg(hash_uniform('k|' || event_id)), 9) AS mean_u FROM {e} GROUP BY 1", e=events)


@query("sql_bloom", f"SELECT p_partkey, {bits('p_name')} AS v FROM part")
def sql_bloom(s, d):
    register_sql(s)
    return s.sql("SELECT p_partkey, bloom50(p_name) AS v FROM {p}", p=table(s, d, "part"))


@query("sql_noise_pad", "SELECT bin, greatest(0, {eta}) AS n_dummy FROM (SELECT range AS bin FROM range(1024))")
def sql_noise_pad(s, d):
    """Dummies of 1,024 bins by the SQL function, equal to those of the padding operator."""
    register_sql(s)
    return s.sql("SELECT id AS bin, noise_pad('1|a|' || id, 14, 0.8D) AS n_dummy FROM range(1024)")


@query("sample_seeded", "SELECT true AS near_share, true AS by_key")
def sample_seeded(s, d):
    """A seeded sample of lines is near its share; by key, every flag has its own share."""
    li = table(s, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_extendedprice", "l_returnflag")
    one = li.sample(0.2, seed=7)
    shares = {"A": 0.5, "N": 0.1}
    n = li.agg(F.count("*").alias("total"), *[F.count_if(F.col("l_returnflag") == k).alias(f"all_{k}") for k in shares])
    got = li.sampleBy("l_returnflag", shares, seed=7).agg(*[F.count_if(F.col("l_returnflag") == k).alias(f"got_{k}") for k in shares])
    near = one.agg(F.count("*").alias("m")).crossJoin(n).crossJoin(got)
    off = lambda got, n, share: F.abs(got - share * n) <= 5 * F.sqrt(n * share * (1 - share)) + 1
    by_key = off(F.col("got_A"), F.col("all_A"), 0.5) & off(F.col("got_N"), F.col("all_N"), 0.1)
    return near.select(off(F.col("m"), F.col("total"), 0.2).alias("near_share"), by_key.alias("by_key"))


# ---- streaming ----------------------------------------------------------------------------------------------------


def _stream(s, d) -> DataFrame:
    """Events as a stream of files, oldest first; timestamps become instants for watermarks."""
    path = daily.lay_out(table(s, d, "events").repartitionByRange(6, "ts").sortWithinPartitions("ts"), shared_path(s, "event-files"))
    return daily.read_events(s, path, EVENTS, 2).withColumn("ts", F.col("ts").cast("timestamp"))


@query("stream_tumbling", "SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling(s, d):
    e = _stream(s, d).groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n"))
    out = e.select(F.col("window.start").alias("start"), "event_type", "n")
    return daily.drain(out, "complete", "tumbling").select(F.to_date("start").cast("string").alias("day"), "event_type", "n")


@query("stream_sliding", "SELECT CAST(epoch(w) AS BIGINT) AS start_s, count(*) AS n FROM (SELECT unnest([date_trunc('hour', ts) - INTERVAL (h) HOUR FOR h IN range(hour(ts) % 6, 24, 6)]) AS w FROM events) GROUP BY 1")
def stream_sliding(s, d):
    e = _stream(s, d).groupBy(F.window("ts", "24 hours", "6 hours")).agg(F.count("*").alias("n"))
    return daily.drain(e.select(F.unix_timestamp("window.start").alias("start_s"), "n"), "complete", "sliding")


@query("stream_session", "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS new FROM events), k AS (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM g) SELECT user_id, count(DISTINCT sid) AS sessions, count(*) AS n FROM k GROUP BY 1")
def stream_session(s, d):
    e = _stream(s, d).groupBy(F.session_window("ts", "2 hours"), "user_id").agg(F.count("*").alias("n"))
    out = daily.drain(e.select("user_id", "n"), "complete", "session")
    return out.groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("n"))


@query("stream_dedup", "SELECT count(DISTINCT event_id) AS n FROM events")
def stream_dedup(s, d):
    e = _stream(s, d)
    twice = e.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2)))).drop("copy")
    once = twice.withWatermark("ts", "1 day").dropDuplicatesWithinWatermark(["event_id"])
    return daily.drain(once.select("event_id"), "append", "dedup").agg(F.count("*").alias("n"))


@query("stream_join", f"WITH {w1()} SELECT count(*) AS n FROM a JOIN b ON a.bin = b.bin AND a.rid = b.rid")
def stream_join(s, d):
    """Records and perturbed copies meet on bin and id within an hour of event time."""
    p = WL.location(s, d)
    side = lambda df: df.select("rid", F.element_at(p.blocking.bins(), 1).alias("bin"))
    when = table(s, d, "events").select(F.col("event_id").alias("rid"), "ts")
    paths = []
    for name, df in (("a", p.a), ("b", p.b)):
        paths.append(daily.lay_out(side(df).join(when, "rid").repartitionByRange(4, "ts"), shared_path(s, f"side-{name}")))
    x, y = (daily.read_events(s, q, "rid long, bin long, ts timestamp_ntz", 2).withColumn("ts", F.col("ts").cast("timestamp")) for q in paths)
    x = x.withWatermark("ts", "2 days").alias("x")
    y = y.withWatermark("ts", "2 days").alias("y")
    on = F.expr("x.bin = y.bin AND x.rid = y.rid AND y.ts >= x.ts - interval 1 hour AND y.ts <= x.ts + interval 1 hour")
    return daily.drain(x.join(y, on).select(F.col("x.rid").alias("rid")), "append", "sjoin").agg(F.count("*").alias("n"))


@query("stream_late", f"WITH {w1()} SELECT (SELECT count(*) FROM a WHERE slot < 8 AND rid % 10 = 0) AS late_rows, (SELECT count(*) FROM a WHERE slot >= 8 OR rid % 10 <> 0) AS released_rows")
def stream_late(s, d):
    """Two days are released when the third is seen, before a tenth of their rows arrives; those rows go to the late table."""
    p = WL.location(s, d)
    rows = p.blocking.assign(p.a).select((F.floor(F.col("slot") / 4)).cast("long").alias("day"), "bin", "rid")
    later = ((F.col("day") < 2) & (F.col("rid") % 10 == 0)) | (F.col("day") > 2)
    path = daily.lay_out(rows.repartitionById(2, later.cast("int")), shared_path(s, "late-files"))
    r = daily.DailyRelease(s, lambda counts, days: counts.select("day", "bin", F.col("n_real").alias("n_noisy")), "late")
    r.run(daily.read_events(s, path, "day long, bin long, rid long")).finish()
    n = r.released().agg(F.sum("n_noisy").alias("released_rows"))
    return r.late().agg(F.count("*").alias("late_rows")).crossJoin(n)


@query("stream_daily_padded", f"WITH {w1()} SELECT CAST(bin // 64 AS BIGINT) AS day, bin, n_noisy FROM (SELECT bin, coalesce(c, 0) + greatest(0, {{eta}}) AS n_noisy FROM dom LEFT JOIN (SELECT bin, count(*) AS c FROM a GROUP BY bin) USING (bin)) WHERE bin < 64 * 29")
def stream_daily_padded(s, d):
    """Padded counts of the closed days, released by ``foreachBatch``, equal the batch release of these days; the last day stays open."""
    from veil.plans.budget import center

    p = WL.location(s, d)
    rows = p.blocking.assign(p.a).select(F.floor(F.col("bin") / 64).cast("long").alias("day"), "bin")
    mu = center(1.6, 1e-5, 2)

    def pad(counts: DataFrame, days: DataFrame) -> DataFrame:
        every = padding.pad_counts(counts.drop("day"), p.blocking, mu, 1.6, "a", 1)
        return every.withColumn("day", F.floor(F.col("bin") / 64).cast("long")).join(days, "day", "left_semi")

    path = daily.lay_out(rows.repartitionById(3, F.floor(F.col("day") / 10).cast("int")), shared_path(s, "day-files"))
    return daily.DailyRelease(s, pad, "padded").run(daily.read_events(s, path, "day long, bin long")).released()


@query(
    "stream_budget",
    "WITH r AS (SELECT o_orderstatus AS party, o_orderkey AS seq, 1 + o_orderkey % 9 AS eps FROM orders), k AS (SELECT *, sum(eps) OVER (PARTITION BY party ORDER BY seq) AS run FROM r) "
    "SELECT party, count(*) AS requests, count(*) FILTER (run <= 2000) AS granted, CAST(coalesce(sum(eps) FILTER (run <= 2000), 0) AS BIGINT) AS spent FROM k GROUP BY party",
)
def stream_budget(s, d):
    """Releases ask for budget in a stream; each party's ledger is state and closes at its cap."""
    asked = table(s, d, "orders").select(F.col("o_orderstatus").alias("party"), F.col("o_orderkey").alias("seq"), (1 + F.col("o_orderkey") % 9).alias("eps"))
    path = daily.lay_out(asked.repartitionByRange(4, "seq"), shared_path(s, "budget-files"))
    out = daily.drain(daily.budget_stream(daily.read_events(s, path, "party string, seq long, eps long"), 2000), "append", "budget")
    return out.groupBy("party").agg(F.count("*").alias("requests"), F.count_if("granted").alias("granted"), F.max("spent").alias("spent"))


def _finish() -> None:
    from veil.plans.catalogue import ORACLES, eta_sql, mu_sql

    ORACLES["sql_noise_pad"] = ORACLES["sql_noise_pad"].replace("{eta}", eta_sql("14", "1.6::DOUBLE", "'1'", "a"))
    ORACLES["stream_daily_padded"] = ORACLES["stream_daily_padded"].replace("{eta}", eta_sql(mu_sql("1.6", "1e-5"), "1.6::DOUBLE", "'1'", "a"))


_finish()
