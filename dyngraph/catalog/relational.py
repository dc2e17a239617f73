"""Queries: the relational operators a user of the graph methods needs, on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import vectors
from ..sources import graphs
from ..sources.tables import materialise, scratch_path, table
from .registry import query

# --- joins


@query("SELECT n_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def j_inner(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "customer", "c_nationkey").join(table(spark, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("customers"))


@query("SELECT c_custkey, count(o_orderkey) AS orders FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY 1")
def j_left(spark: SparkSession, d: str) -> DataFrame:
    o = table(spark, d, "orders", "o_custkey", "o_orderkey").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"))
    return table(spark, d, "customer", "c_custkey").join(o, F.col("c_custkey") == F.col("o_custkey"), "left").select("c_custkey", F.coalesce("n", F.lit(0)).alias("orders"))


@query("SELECT coalesce(a.k, b.k) AS k, a.n AS customers, b.n AS suppliers FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer WHERE c_acctbal > 9000 GROUP BY 1) a FULL JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier WHERE s_acctbal > 5000 GROUP BY 1) b ON a.k = b.k")
def j_full(spark: SparkSession, d: str) -> DataFrame:
    a = table(spark, d, "customer", "c_nationkey", "c_acctbal").filter("c_acctbal > 9000").groupBy(F.col("c_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("customers"))
    b = table(spark, d, "supplier", "s_nationkey", "s_acctbal").filter("s_acctbal > 5000").groupBy(F.col("s_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("suppliers"))
    return a.join(b, "k", "full")


@query("SELECT c_custkey FROM customer SEMI JOIN (SELECT * FROM orders WHERE o_orderstatus = 'F') o ON o.o_custkey = c_custkey")
def j_semi(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "customer", "c_custkey").join(table(spark, d, "orders", "o_custkey", "o_orderstatus").filter("o_orderstatus = 'F'"), F.col("c_custkey") == F.col("o_custkey"), "left_semi")


@query("SELECT c_custkey FROM customer ANTI JOIN (SELECT * FROM orders WHERE o_orderstatus = 'F') o ON o.o_custkey = c_custkey")
def j_anti(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "customer", "c_custkey").join(table(spark, d, "orders", "o_custkey", "o_orderstatus").filter("o_orderstatus = 'F'"), F.col("c_custkey") == F.col("o_custkey"), "left_anti")


@query("SELECT CAST(p.part AS INTEGER) AS part, r_name FROM range(4) p(part) CROSS JOIN region")
def j_cross(spark: SparkSession, d: str) -> DataFrame:
    """Clients by classes: both sides are of fixed size."""
    return spark.range(4).select(F.col("id").cast("int").alias("part")).crossJoin(F.broadcast(table(spark, d, "region", "r_name")))


@query("SELECT t.snap, count(*) AS live FROM (SELECT CAST(r AS INTEGER) AS snap FROM range(0, 40) q(r)) t JOIN (SELECT o_orderkey, CAST((year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 AS INTEGER) AS since FROM orders) o ON t.snap BETWEEN o.since AND o.since + 2 GROUP BY 1")
def j_range(spark: SparkSession, d: str) -> DataFrame:
    """Validity intervals of three months: each row is dealt to its buckets, then joined by equality."""
    o = table(spark, d, "orders", "o_orderdate").select(graphs.month("o_orderdate").alias("since"))
    counted = o.groupBy("since").agg(F.count(F.lit(1)).alias("n"))
    live = counted.select("n", F.explode(F.sequence(F.col("since"), F.col("since") + 2)).alias("snap"))
    return live.join(F.broadcast(spark.range(40).select(F.col("id").cast("int").alias("snap"))), "snap").groupBy("snap").agg(F.sum("n").alias("live"))


@query("SELECT p.event_id, q.event_id AS last_purchase FROM events p ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'purchase' GROUP BY 1, 2) q ON p.user_id = q.user_id AND p.ts > q.ts")
def j_asof(spark: SparkSession, d: str) -> DataFrame:
    """Latest purchase before each event of the same user: one sorted pass over the union, no inequality join."""
    e = table(spark, d, "events", "event_id", "ts", "user_id", "event_type")
    left = e.select("user_id", "ts", F.col("event_id").alias("lid"), F.lit(None).cast("long").alias("rid"), F.lit(0).alias("side"))
    right = e.filter("event_type = 'purchase'").select("user_id", "ts", F.lit(None).cast("long").alias("lid"), F.col("event_id").alias("rid"), F.lit(1).alias("side"))
    order = Window.partitionBy("user_id").orderBy("ts", "side", "rid").rowsBetween(Window.unboundedPreceding, -1)
    both = left.unionAll(right).withColumn("found", F.last("rid", ignorenulls=True).over(order))
    return both.filter("side = 0").select(F.col("lid").alias("event_id"), F.col("found").alias("last_purchase"))


@query("SELECT p.event_id AS a, q.event_id AS b FROM events p JOIN events q ON p.event_type = q.event_type AND p.user_id < q.user_id AND q.ts >= p.ts AND q.ts <= p.ts + INTERVAL 10 MINUTE")
def j_interval(spark: SparkSession, d: str) -> DataFrame:
    """Events of one type within ten minutes: time is bucketed, and the later side looks in its bucket and the one before."""
    e = table(spark, d, "events", "event_id", "ts", "user_id", "event_type").withColumn("s", F.unix_micros(F.col("ts").cast("timestamp")))
    bucket = F.floor(F.col("s") / 600_000_000)
    left = e.select("event_type", F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("s").alias("sa"), bucket.alias("k"))
    right = e.select("event_type", F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("s").alias("sb"), F.explode(F.array(bucket, bucket - 1)).alias("k"))
    return left.join(right, ["event_type", "k"]).filter("ua < ub and sb between sa and sa + 600000000").select("a", "b")


@query("SELECT count(*) AS pairs FROM (SELECT CASE WHEN n_nationkey % 5 = 0 THEN NULL ELSE n_regionkey END AS k FROM nation) a JOIN (SELECT CASE WHEN r_regionkey = 2 THEN NULL ELSE r_regionkey END AS k FROM region) b ON a.k IS NOT DISTINCT FROM b.k")
def j_nullsafe(spark: SparkSession, d: str) -> DataFrame:
    a = table(spark, d, "nation").select(F.when(F.col("n_nationkey") % 5 != 0, F.col("n_regionkey")).alias("k"))
    b = table(spark, d, "region").select(F.when(F.col("r_regionkey") != 2, F.col("r_regionkey")).alias("k2"))
    return a.join(b, F.col("k").eqNullSafe(F.col("k2"))).agg(F.count(F.lit(1)).alias("pairs"))


@query("SELECT r_name, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def j_broadcast(spark: SparkSession, d: str) -> DataFrame:
    n = table(spark, d, "nation").join(F.broadcast(table(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    c = table(spark, d, "customer", "c_custkey", "c_nationkey").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey"))
    return table(spark, d, "orders", "o_custkey", "o_totalprice").join(c, F.col("o_custkey") == F.col("c_custkey")).groupBy("r_name").agg(F.round(F.sum("o_totalprice"), 2).alias("total"))


# --- aggregates


def _placed_orders(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders", "o_custkey", "o_orderstatus", "o_orderpriority").select((F.col("o_custkey") % 4).cast("int").alias("part"), "o_orderstatus", "o_orderpriority")


for _n, _sql, _f in (
    ("a_rollup", "ROLLUP(1, 2)", lambda df: df.rollup("part", "o_orderstatus")),
    ("a_cube", "CUBE(1, 2)", lambda df: df.cube("part", "o_orderstatus")),
    ("a_sets", "GROUPING SETS ((1), (2))", lambda df: df.groupingSets([["part"], ["o_orderstatus"]], "part", "o_orderstatus")),
):
    query(f"SELECT CAST(o_custkey % 4 AS INTEGER) AS part, o_orderstatus, count(*) AS n FROM orders GROUP BY {_sql.replace('1', 'CAST(o_custkey % 4 AS INTEGER)').replace('2', 'o_orderstatus')}", name=_n)(
        lambda spark, d, _f=_f: _f(_placed_orders(spark, d)).agg(F.count(F.lit(1)).alias("n"))
    )


@query("SELECT o_orderstatus, count(DISTINCT o_custkey) AS customers FROM orders GROUP BY 1")
def a_distinct(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders", "o_custkey", "o_orderstatus").groupBy("o_orderstatus").agg(F.count_distinct("o_custkey").alias("customers"))


@query("SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o FROM orders GROUP BY 1")
def a_filter(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders", "o_orderpriority", "o_orderstatus").groupBy("o_orderpriority").agg(F.count_if(F.col("o_orderstatus") == "F").alias("f"), F.count_if(F.col("o_orderstatus") == "O").alias("o"))


@query("SELECT CAST(o_custkey % 4 AS INTEGER) AS part, count(*) FILTER (o_orderstatus = 'F') AS F, count(*) FILTER (o_orderstatus = 'O') AS O, count(*) FILTER (o_orderstatus = 'P') AS P FROM orders GROUP BY 1")
def a_pivot(spark: SparkSession, d: str) -> DataFrame:
    return _placed_orders(spark, d).groupBy("part").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).fillna(0)


@query("SELECT s_suppkey, name, value FROM (SELECT s_suppkey, s_acctbal, CAST(s_nationkey AS DOUBLE) AS nation FROM supplier) UNPIVOT (value FOR name IN (s_acctbal, nation))")
def a_unpivot(spark: SparkSession, d: str) -> DataFrame:
    s = table(spark, d, "supplier", "s_suppkey", "s_acctbal", "s_nationkey").select("s_suppkey", "s_acctbal", F.col("s_nationkey").cast("double").alias("nation"))
    return s.unpivot("s_suppkey", ["s_acctbal", "nation"], "name", "value")


@query("SELECT p_type, round(quantile_cont(p_retailprice, 0.5), 6) AS median, round(quantile_cont(p_retailprice, 0.9), 6) AS p90 FROM part GROUP BY 1")
def a_percentile(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "part", "p_type", "p_retailprice").groupBy("p_type").agg(F.round(F.percentile("p_retailprice", F.lit(0.5)), 6).alias("median"), F.round(F.percentile("p_retailprice", F.lit(0.9)), 6).alias("p90"))


@query("SELECT o_custkey, arg_max(o_orderkey, (o_orderdate, o_orderkey)) AS latest, arg_min(o_orderkey, (o_orderdate, o_orderkey)) AS earliest FROM orders GROUP BY 1")
def a_maxby(spark: SparkSession, d: str) -> DataFrame:
    at = F.struct("o_orderdate", "o_orderkey")
    return table(spark, d, "orders", "o_custkey", "o_orderkey", "o_orderdate").groupBy("o_custkey").agg(F.max_by("o_orderkey", at).alias("latest"), F.min_by("o_orderkey", at).alias("earliest"))


@query("SELECT c_nationkey, string_agg(c_mktsegment || '=' || n, ',' ORDER BY c_mktsegment) AS histogram FROM (SELECT c_nationkey, c_mktsegment, count(*) AS n FROM customer GROUP BY 1, 2) GROUP BY 1")
def a_hist_map(spark: SparkSession, d: str) -> DataFrame:
    """Class histogram of each client, as a map rendered in order of class."""
    n = table(spark, d, "customer", "c_nationkey", "c_mktsegment").groupBy("c_nationkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))
    m = n.groupBy("c_nationkey").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("c_mktsegment", "n")))).alias("m"))
    return m.select("c_nationkey", F.array_join(F.transform(F.map_entries("m"), lambda x: F.concat_ws("=", x["key"], x["value"])), ",").alias("histogram"))


@query("SELECT p_brand, round(stddev_pop(p_retailprice), 6) AS sd, round(corr(p_size, p_retailprice), 6) AS r, bool_and(p_size > 0) AS positive FROM part GROUP BY 1")
def a_moments(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "part", "p_brand", "p_size", "p_retailprice").groupBy("p_brand").agg(
        F.round(F.stddev_pop("p_retailprice"), 6).alias("sd"), F.round(F.corr("p_size", "p_retailprice"), 6).alias("r"), F.bool_and(F.col("p_size") > 0).alias("positive")
    )


@query("SELECT true AS near")
def a_sketch_distinct(spark: SparkSession, d: str) -> DataFrame:
    """Approximate distinct count of customers with orders lies within a tenth of the exact one."""
    o = table(spark, d, "orders", "o_custkey").agg(F.approx_count_distinct("o_custkey", 0.02).alias("a"), F.count_distinct("o_custkey").alias("e"))
    return o.select((F.abs(F.col("a") - F.col("e")) <= 0.1 * F.col("e")).alias("near"))


@query("SELECT true AS near")
def a_sketch_merge(spark: SparkSession, d: str) -> DataFrame:
    """Sketches of clients merge into one of the whole."""
    o = table(spark, d, "orders", "o_custkey").groupBy((F.col("o_custkey") % 4).alias("part")).agg(F.hll_sketch_agg("o_custkey", 14).alias("s"))
    e = table(spark, d, "orders", "o_custkey").agg(F.count_distinct("o_custkey").alias("e"))
    merged = o.agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("a"))
    return merged.join(F.broadcast(e)).select((F.abs(F.col("a") - F.col("e")) <= 0.1 * F.col("e")).alias("near"))


# --- windows


@query("SELECT c_custkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, round(percent_rank() OVER v, 6) AS pr, round(cume_dist() OVER v, 6) AS cd FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_mktsegment, c_custkey), v AS (PARTITION BY c_nationkey ORDER BY c_mktsegment)")
def w_rank_family(spark: SparkSession, d: str) -> DataFrame:
    v = Window.partitionBy("c_nationkey").orderBy("c_mktsegment")
    w = Window.partitionBy("c_nationkey").orderBy("c_mktsegment", "c_custkey")
    return table(spark, d, "customer", "c_custkey", "c_nationkey", "c_mktsegment").select(
        "c_custkey", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(v).cast("long").alias("rk"), F.dense_rank().over(v).cast("long").alias("dr"),
        F.round(F.percent_rank().over(v), 6).alias("pr"), F.round(F.cume_dist().over(v), 6).alias("cd"),
    )


@query("SELECT event_id, lag(value) OVER w AS before, lead(value, 2) OVER w AS later FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def w_lag_lead(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, d, "events", "event_id", "user_id", "ts", "value").select("event_id", F.lag("value").over(w).alias("before"), F.lead("value", 2).over(w).alias("later"))


@query("SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING) AS nth FROM orders")
def w_running(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    return table(spark, d, "orders", "o_orderkey", "o_custkey", "o_orderdate").select("o_orderkey", F.count(F.lit(1)).over(w).alias("nth"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS n FROM events")
def w_range_frame(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)
    return table(spark, d, "events", "event_id", "user_id", "ts").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp"))).select("event_id", F.count(F.lit(1)).over(w).alias("n"))


@query("SELECT p_partkey, CAST(ntile(10) OVER (PARTITION BY p_brand ORDER BY p_partkey) AS INTEGER) AS bucket FROM part")
def w_ntile(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "part", "p_partkey", "p_brand").select("p_partkey", F.ntile(10).over(Window.partitionBy("p_brand").orderBy("p_partkey")).alias("bucket"))


@query("WITH d AS (SELECT DISTINCT user_id, CAST(date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS INTEGER) AS day FROM events), g AS (SELECT *, day - row_number() OVER (PARTITION BY user_id ORDER BY day) AS g FROM d) SELECT user_id, CAST(min(day) AS INTEGER) AS since, CAST(max(day) AS INTEGER) AS until FROM g GROUP BY user_id, g")
def w_islands(spark: SparkSession, d: str) -> DataFrame:
    days = table(spark, d, "events", "user_id", "ts").select("user_id", graphs.day("ts").alias("day")).distinct()
    g = days.withColumn("g", F.col("day") - F.row_number().over(Window.partitionBy("user_id").orderBy("day")))
    return g.groupBy("user_id", "g").agg(F.min("day").alias("since"), F.max("day").alias("until")).select("user_id", "since", "until")


@query("SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS latest FROM events")
def w_last_known(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    e = table(spark, d, "events", "event_id", "user_id", "ts", "event_type")
    return e.select("event_id", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w).alias("latest"))


# --- sets, sorting


def _nations(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    return table(spark, d, "customer", "c_nationkey").select(F.col("c_nationkey").alias("k")), table(spark, d, "supplier", "s_nationkey").filter("s_nationkey < 12").select(F.col("s_nationkey").alias("k"))


_A, _B = "SELECT c_nationkey AS k FROM customer", "SELECT s_nationkey AS k FROM supplier WHERE s_nationkey < 12"
for _n, _op, _f in (
    ("s_union", "UNION", lambda a, b: a.union(b).distinct()),
    ("s_union_all", "UNION ALL", lambda a, b: a.unionAll(b)),
    ("s_intersect", "INTERSECT", lambda a, b: a.intersect(b)),
    ("s_intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)),
    ("s_except", "EXCEPT", lambda a, b: a.subtract(b)),
    ("s_except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b)),
):
    query(f"{_A} {_op} {_B}", name=_n)(lambda spark, d, _f=_f: _f(*_nations(spark, d)))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def t_global(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20)


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 20")
def t_offset(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(20).limit(20)


@query("SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate DESC, o_orderkey) AS r FROM orders) WHERE r <= 3")
def t_per_group(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_orderdate"), "o_orderkey")
    return table(spark, d, "orders", "o_custkey", "o_orderkey", "o_orderdate").withColumn("r", F.row_number().over(w)).filter("r <= 3").select("o_custkey", "o_orderkey")


# --- scalar functions


@query("SELECT page_id, lower(trim(url)) AS u, length(html) AS n, split_part(url, '/', 3) AS host, substr(url, 1, 5) AS head, regexp_matches(url, '[0-9]{3}') AS has, concat('<', substr(url, 9, 4), '>') AS c, md5(url) AS h FROM pages")
def f_string(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "pages").select(
        "page_id", F.lower(F.trim("url")).alias("u"), F.length("html").cast("long").alias("n"), F.split_part("url", F.lit("/"), F.lit(3)).alias("host"), F.substring("url", 1, 5).alias("head"),
        F.col("url").rlike("[0-9]{3}").alias("has"), F.concat(F.lit("<"), F.substring("url", 9, 4), F.lit(">")).alias("c"), F.md5("url").alias("h"),
    )


@query("SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS m, CAST(year(o_orderdate) * 12 + month(o_orderdate) AS INTEGER) AS idx, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days, CAST(dayofmonth(o_orderdate) AS INTEGER) AS dom, CAST(CAST(o_orderdate AS DATE) + INTERVAL 30 DAY AS DATE) AS due FROM orders")
def f_date(spark: SparkSession, d: str) -> DataFrame:
    o = "o_orderdate"
    return table(spark, d, "orders", "o_orderkey", o).select(
        "o_orderkey", F.trunc(o, "month").alias("m"), (F.year(o) * 12 + F.month(o)).alias("idx"), F.datediff(F.to_date(o), F.lit("1995-01-01").cast("date")).alias("days"), F.dayofmonth(o).alias("dom"), F.date_add(F.to_date(o), 30).alias("due")
    )


@query("SELECT p_partkey, round(log2(p_size), 6) AS l, round(exp(-p_size / 10.0), 6) AS e, round(sqrt(p_retailprice), 6) AS s, round(tanh(p_size / 50.0), 6) AS t, round(1 / (1 + exp(-p_size / 25.0)), 6) AS g, CAST(p_partkey % 7 AS BIGINT) AS m, p_partkey & 12 AS b, greatest(p_size, 25) AS hi, least(p_size, 25) AS lo FROM part")
def f_math(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "part", "p_partkey", "p_size", "p_retailprice").select(
        "p_partkey", F.round(F.log2("p_size"), 6).alias("l"), F.round(F.exp(-F.col("p_size") / 10.0), 6).alias("e"), F.round(F.sqrt("p_retailprice"), 6).alias("s"), F.round(F.tanh(F.col("p_size") / 50.0), 6).alias("t"),
        F.round(vectors.sigmoid(F.col("p_size") / 25.0), 6).alias("g"), F.pmod("p_partkey", F.lit(7)).cast("long").alias("m"), F.col("p_partkey").bitwiseAND(12).alias("b"), F.greatest("p_size", F.lit(25)).alias("hi"), F.least("p_size", F.lit(25)).alias("lo"),
    )


@query("SELECT vec_id, round(list_inner_product(e, e), 5) AS dot, round(list_cosine_similarity(e[1:32], e[33:64]), 5) AS cos, CAST(list_position(e, list_max(e)) - 1 AS BIGINT) AS arg, CAST(len(list_filter(e, lambda x: x > 0)) AS INTEGER) AS pos, round(list_sum(list_transform(e[1:8], lambda x: x * 2)), 5) AS twice FROM (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings)")
def f_array(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "embeddings", "vec_id", "embedding").select("vec_id", F.col("embedding").cast("array<double>").alias("e"))
    return e.select(
        "vec_id", F.round(vectors.dot("e", "e"), 5).alias("dot"), F.round(vectors.cosine(F.slice("e", 1, 32), F.slice("e", 33, 32)), 5).alias("cos"), vectors.argmax("e").cast("long").alias("arg"),
        F.size(F.filter("e", lambda x: x > 0)).alias("pos"), F.round(F.aggregate(F.transform(F.slice("e", 1, 8), lambda x: x * 2), F.lit(0.0), lambda a, x: a + x), 5).alias("twice"),
    )


@query("SELECT o_orderkey, CAST(CASE o_orderstatus WHEN 'F' THEN 1 ELSE 0 END AS VARCHAR) || CAST(CASE o_orderstatus WHEN 'O' THEN 1 ELSE 0 END AS VARCHAR) || CAST(CASE o_orderstatus WHEN 'P' THEN 1 ELSE 0 END AS VARCHAR) AS hot FROM orders")
def f_one_hot(spark: SparkSession, d: str) -> DataFrame:
    y = F.array_position(F.array(F.lit("F"), F.lit("O"), F.lit("P")), F.col("o_orderstatus")) - 1
    return table(spark, d, "orders", "o_orderkey", "o_orderstatus").select("o_orderkey", F.array_join(F.transform(vectors.one_hot(y, 3), lambda v: v.cast("string")), "").alias("hot"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events")
def f_json(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events", "event_id", "props").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events")
def f_variant(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events", "event_id", "props").select("event_id", F.try_variant_get(F.try_parse_json("props"), "$.k", "int").alias("k"))


@query("SELECT c_custkey, CAST(('0x' || substr(md5(CAST(c_custkey AS VARCHAR)), 1, 13)) AS BIGINT) AS h FROM customer WHERE CAST(('0x' || substr(md5(CAST(c_custkey AS VARCHAR)), 1, 13)) AS BIGINT) % 10 < 3")
def f_hash_pick(spark: SparkSession, d: str) -> DataFrame:
    """A repeatable sample of three tenths: the sampling operator, by digest rather than by random order."""
    h = graphs.hashed(F.col("c_custkey").cast("string"))
    return table(spark, d, "customer", "c_custkey").select("c_custkey", h.alias("h")).filter("h % 10 < 3")


@query("SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal BETWEEN 0 AND 5000 THEN 'low' ELSE 'high' END AS band, c_mktsegment IN ('BUILDING', 'MACHINERY') AS chosen, c_name LIKE '%1%' AS has_one FROM customer WHERE c_nationkey IS NOT NULL")
def f_conditions(spark: SparkSession, d: str) -> DataFrame:
    c = table(spark, d, "customer").filter("c_nationkey is not null")
    band = F.when(F.col("c_acctbal") < 0, "debt").when(F.col("c_acctbal").between(0, 5000), "low").otherwise("high")
    return c.select("c_custkey", band.alias("band"), F.col("c_mktsegment").isin("BUILDING", "MACHINERY").alias("chosen"), F.col("c_name").like("%1%").alias("has_one"))


# --- sources and sinks: a table written in a format and read back


def _round_trip(fmt: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        df = table(spark, d, "supplier", "s_suppkey", "s_name", "s_nationkey", "s_acctbal")
        path = scratch_path(spark, fmt)
        df.write.format(fmt).option("header", "true").save(path)
        return spark.read.format(fmt).option("header", "true").schema(df.schema).load(path)

    return run


for _fmt in ("csv", "json", "orc", "parquet"):
    query("SELECT s_suppkey, s_name, s_nationkey, s_acctbal FROM supplier", name=f"io_{_fmt}")(_round_trip(_fmt))


@query("SELECT l_orderkey * 8 + 1 AS x, l_partkey * 8 + 2 AS y, CAST((year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 AS INTEGER) AS snap FROM lineitem WHERE (year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 = 40")
def io_partitioned(spark: SparkSession, d: str) -> DataFrame:
    """Edge events written by snapshot; the filter prunes all other folders."""
    return materialise(graphs.ship(spark, d).repartition("snap"), "by_snap", by="snap").filter("snap = 40")
