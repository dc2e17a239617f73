"""Queries: graph builders, snapshots, regions, clients, message passing, exchange."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import cost, quality
from ..operators import clients, exchange, message, recurrent, region, snapshots
from ..sources import graphs
from ..sources.tables import materialise, table
from . import sql
from .registry import query

for _name in graphs.BUILDERS:
    query(sql.edges(_name) + " ", name=f"edges_{_name}" + "_topk" * (_name == "vec"))(lambda spark, d, _n=_name: graphs.edges(spark, d, _n))


@query("SELECT vid, n FROM (SELECT vid, count(*) AS n FROM (SELECT DISTINCT a AS vid, b FROM (" + sql.edges("vec") + ")) GROUP BY 1) WHERE n < 0")
def edges_vec_hashed_missed(spark: SparkSession, d: str) -> DataFrame:
    """Empty while hashing finds at least nine tenths of the exact neighbours, else the vertices that miss some."""
    exact = materialise(graphs.vec(spark, d).select("x", "y"), "exact")
    found = graphs.vec_hashed(spark, d, bits=3, tables=24).select("x", "y")
    lost = materialise(exact.join(found, ["x", "y"], "left_anti").groupBy(F.col("x").alias("vid")).agg(F.count(F.lit(1)).alias("n")), "lost")
    most = exact.agg((F.count(F.lit(1)) * 0.1).alias("m")).select("m").scalar()
    total = lost.agg(F.sum("n").alias("t")).select("t").scalar()
    return lost.filter(F.coalesce(total, F.lit(0)) > most)


# --- snapshots


@query(f"SELECT CAST(t.snap AS INTEGER) AS snap, count(*) AS edges FROM range(10) t(snap) JOIN ({sql.edges('copurchase')}) e ON e.first <= t.snap GROUP BY 1")
def snap_cumulative_sizes(spark: SparkSession, d: str) -> DataFrame:
    e = graphs.edges(spark, d, "copurchase")
    new = e.groupBy("first").agg(F.count(F.lit(1)).alias("n"))
    every = spark.range(10).select(F.col("id").cast("int").alias("snap"))
    return every.join(F.broadcast(new), F.col("first") <= F.col("snap")).groupBy("snap").agg(F.sum("n").alias("edges"))


_SLIDING = f"""SELECT a, b, CAST(min(snap) AS INTEGER) AS since, CAST(max(snap) + 2 AS INTEGER) AS until FROM (
SELECT *, sum(fresh) OVER (PARTITION BY a, b ORDER BY snap) AS island FROM (
SELECT a, b, snap, CASE WHEN snap > coalesce(lag(snap) OVER (PARTITION BY a, b ORDER BY snap), -1000000000) + 3 THEN 1 ELSE 0 END AS fresh
FROM (SELECT DISTINCT least(x, y) AS a, greatest(x, y) AS b, snap FROM ({sql.EVENTS['talk']})))) GROUP BY a, b, island"""


def churn(spark: SparkSession, d: str) -> DataFrame:
    """Daily talk edges that live three days."""
    ev = graphs.talk(spark, d)
    return snapshots.sliding(ev.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), "snap"), 3)


@query(_SLIDING)
def snap_sliding_validity(spark: SparkSession, d: str) -> DataFrame:
    return churn(spark, d)


@query(f"SELECT a, b, '+' AS op FROM ({sql.edges('copurchase')}) WHERE first = 5")
def snap_delta_added(spark: SparkSession, d: str) -> DataFrame:
    return snapshots.delta(graphs.edges(spark, d, "copurchase"), 5)


@query(f"WITH c AS MATERIALIZED ({_SLIDING}), n AS (SELECT a, b FROM c WHERE 9 BETWEEN since AND until), p AS (SELECT a, b FROM c WHERE 8 BETWEEN since AND until) SELECT a, b, '+' AS op FROM n ANTI JOIN p USING (a, b) UNION ALL SELECT a, b, '-' FROM p ANTI JOIN n USING (a, b)")
def snap_delta_removed(spark: SparkSession, d: str) -> DataFrame:
    return snapshots.delta(churn(spark, d), 9)


def _daily_counts(spark: SparkSession, d: str, day: int) -> DataFrame:
    e = table(spark, d, "events", "user_id", "ts").filter(graphs.day("ts") == day)
    return e.groupBy(graphs.vid("user_id", "user").alias("vid")).agg(F.count(F.lit(1)).alias("x"))


def _day_sql(k: int) -> str:
    return f"SELECT user_id * 8 + 4 AS vid, count(*) AS x FROM events WHERE {sql.DAY.format('ts')} = {k} GROUP BY 1"


@query(f"SELECT p.vid FROM ({_day_sql(7)}) p JOIN ({_day_sql(8)}) q USING (vid) WHERE p.x IS DISTINCT FROM q.x")
def snap_delta_changed(spark: SparkSession, d: str) -> DataFrame:
    return snapshots.changed(_daily_counts(spark, d, 7), _daily_counts(spark, d, 8))


@query(f"SELECT vid, CAST(min(first) AS INTEGER) AS first FROM (SELECT a AS vid, first FROM ({sql.edges('copurchase')}) UNION ALL SELECT b, first FROM ({sql.edges('copurchase')})) GROUP BY 1")
def snap_vertex_arrivals(spark: SparkSession, d: str) -> DataFrame:
    return snapshots.arrivals(graphs.edges(spark, d, "copurchase"))


@query(f"SELECT {sql.decile('page_id', 'pages')} AS snap, count(*) AS pages FROM pages GROUP BY 1")
def snap_rank_buckets(spark: SparkSession, d: str) -> DataFrame:
    p = table(spark, d, "pages", "page_id")
    return p.groupBy(graphs.decile("page_id", p).alias("snap")).agg(F.count(F.lit(1)).alias("pages"))


@query("SELECT CAST(floor(date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) / 5) AS INTEGER) AS snap, count(*) AS events FROM events GROUP BY 1")
def snap_calendar_windows(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events", "ts").groupBy(snapshots.window_of("ts", 5, "2024-01-01").alias("snap")).agg(F.count(F.lit(1)).alias("events"))


# --- regions, on weekly purchases up to week 171

_WEEK = graphs.undirected


def _weekly(spark: SparkSession, d: str) -> DataFrame:
    return graphs.undirected(graphs.buy(spark, d, "week"))


_R = sql.base("buy_week", where="first <= 171") + """,
touched AS MATERIALIZED (SELECT DISTINCT src AS vid FROM s WHERE first = 171),
r1 AS MATERIALIZED (SELECT vid, 1 AS hop FROM (SELECT DISTINCT dst AS vid FROM s JOIN touched ON touched.vid = s.src) ANTI JOIN touched USING (vid)),
k1 AS MATERIALIZED (SELECT vid, 0 AS hop FROM touched UNION ALL SELECT vid, hop FROM r1),
r2 AS MATERIALIZED (SELECT vid, 2 AS hop FROM (SELECT DISTINCT dst AS vid FROM s JOIN r1 ON r1.vid = s.src) ANTI JOIN k1 USING (vid)),
k2 AS MATERIALIZED (SELECT * FROM k1 UNION ALL SELECT vid, hop FROM r2)"""


def _now(spark: SparkSession, d: str) -> DataFrame:
    return snapshots.at(_weekly(spark, d), 171)


@query(f"SELECT vid FROM (SELECT vid, min(first) AS first FROM (SELECT a AS vid, first FROM ({sql.edges('buy_week')}) UNION ALL SELECT b, first FROM ({sql.edges('buy_week')})) GROUP BY 1) WHERE first = 171")
def region_seeds_new(spark: SparkSession, d: str) -> DataFrame:
    return region.seeds(_weekly(spark, d), 171, "new_vertices")


@query(_R + " SELECT vid FROM touched")
def region_seeds_touched(spark: SparkSession, d: str) -> DataFrame:
    return region.seeds(_weekly(spark, d), 171)


@query(_R + " SELECT vid, CAST(hop AS INTEGER) AS hop FROM k1")
def region_khop1(spark: SparkSession, d: str) -> DataFrame:
    return region.khop(_now(spark, d), region.seeds(_weekly(spark, d), 171), 1)


@query(_R + " SELECT vid, CAST(hop AS INTEGER) AS hop FROM k2")
def region_khop2(spark: SparkSession, d: str) -> DataFrame:
    return region.khop(_now(spark, d), region.seeds(_weekly(spark, d), 171), 2)


@query(_R + " SELECT a, b, first FROM e SEMI JOIN k2 ON e.a = k2.vid SEMI JOIN k2 AS j2 ON e.b = j2.vid")
def region_induced_edges(spark: SparkSession, d: str) -> DataFrame:
    now = _now(spark, d)
    return region.induce(now, region.khop(now, region.seeds(_weekly(spark, d), 171), 2))


@query(_R + " SELECT CAST(1 AS INTEGER) AS layer, vid FROM touched UNION ALL SELECT 2, vid FROM k1")
def region_ring_layers(spark: SparkSession, d: str) -> DataFrame:
    return region.rings(_now(spark, d), region.seeds(_weekly(spark, d), 171), 2)


@query(_R + """, i AS (SELECT count(*) AS n FROM e SEMI JOIN k2 ON e.a = k2.vid SEMI JOIN k2 AS j2 ON e.b = j2.vid)
SELECT (SELECT count(*) FROM v) AS vertices, (SELECT count(*) FROM e) AS edges, (SELECT count(*) FROM k2) AS region_vertices, i.n AS region_edges,
round((SELECT count(*) FROM k2) / (SELECT count(*) FROM v), 6) AS share FROM i""")
def region_locality(spark: SparkSession, d: str) -> DataFrame:
    now = _now(spark, d)
    return region.locality(now, region.khop(now, region.seeds(_weekly(spark, d), 171), 2))


@query(sql.base("reply") + ", w AS (SELECT 6 AS vid, 0 AS hop UNION SELECT s.dst, w.hop + 1 FROM w JOIN s ON s.src = w.vid WHERE w.hop < 6) SELECT CAST(vid AS BIGINT) AS vid, CAST(min(hop) AS INTEGER) AS hop FROM w WHERE vid IN (SELECT vid FROM v) GROUP BY 1")
def region_recursive_reach(spark: SparkSession, d: str) -> DataFrame:
    """Reach of one vertex over six hops, as a recursive query in SQL."""
    graphs.symmetric(graphs.edges(spark, d, "reply")).createOrReplaceTempView("_reach_edges")
    return spark.sql(
        "WITH RECURSIVE w(vid, hop) AS (SELECT 6L, 0 UNION ALL SELECT s.dst, w.hop + 1 FROM w JOIN _reach_edges s ON s.src = w.vid WHERE w.hop < 6)"
        " SELECT vid, min(hop) AS hop FROM w WHERE vid IN (SELECT src FROM _reach_edges) GROUP BY vid"
    )


# --- clients, on co-purchases


def placed(spark: SparkSession, d: str, name: str = "copurchase", t: int | None = None, m: int = 4) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Edges with clients, assignment and features of a graph under the fixed assignment."""
    e = graphs.edges(spark, d, name)
    e = materialise(e if t is None else snapshots.at(e, t), "edges")
    v = graphs.vertices(e)
    asg = graphs.by_key(v, m)
    feats = graphs.small_feature(v).select("vid", F.array("x").alias("x"))
    return materialise(clients.placed(e, asg), "placed"), asg, feats


_C = sql.base("copurchase")


@query(_C + " SELECT src, dst, first, pu, pv FROM ee WHERE pu = pv")
def client_local_edges(spark: SparkSession, d: str) -> DataFrame:
    return clients.local(placed(spark, d)[0])


@query(_C + " SELECT src, dst, first, pu, pv FROM ee WHERE pu <> pv")
def client_cut_edges(spark: SparkSession, d: str) -> DataFrame:
    return clients.cut(placed(spark, d)[0])


@query(_C + " SELECT DISTINCT src AS vid, pu AS part FROM ee WHERE pu <> pv")
def client_border(spark: SparkSession, d: str) -> DataFrame:
    return clients.border(placed(spark, d)[0])


@query(_C + " SELECT src AS vid, count(*) AS remote FROM ee WHERE pu <> pv GROUP BY 1")
def client_remote_neighbours(spark: SparkSession, d: str) -> DataFrame:
    return clients.remote_neighbours(placed(spark, d)[0])


@query(_C + " SELECT vid, count(part) AS clients FROM v LEFT JOIN asg USING (vid) GROUP BY 1 HAVING count(part) <> 1")
def client_cover_check(spark: SparkSession, d: str) -> DataFrame:
    _, asg, feats = placed(spark, d)
    return clients.cover_faults(feats.select("vid"), asg)


# --- message passing

_S = sql.base("copurchase") + sql.SUMS


def _scalar(df: DataFrame) -> DataFrame:
    return df.select("vid", F.get("x", F.lit(0)).alias("x"))


@query(_S + " SELECT vid, x FROM g1")
def mp_sum_hop1(spark: SparkSession, d: str) -> DataFrame:
    ee, _, x = placed(spark, d)
    return _scalar(message.aggregate(ee, x, "sum", d=1))


@query(_S + " SELECT vid, x FROM g2")
def mp_sum_hop2(spark: SparkSession, d: str) -> DataFrame:
    ee, _, x = placed(spark, d)
    return _scalar(message.aggregate(ee, message.aggregate(ee, x, "sum", d=1), "sum", d=1))


@query(_S + " SELECT g1.vid, round(g1.x / (d.deg + 1), 6) AS x FROM g1 JOIN d USING (vid)")
def mp_mean_hop1(spark: SparkSession, d: str) -> DataFrame:
    ee, _, x = placed(spark, d)
    return message.aggregate(ee, x, "mean", d=1).select("vid", F.round(F.get("x", F.lit(0)), 6).alias("x"))


@query(_S + ", n AS (SELECT vid, f.x / sqrt(deg + 1) AS x, deg FROM f JOIN d USING (vid)) SELECT n.vid, round((n.x + t.x) / sqrt(n.deg + 1), 6) AS x FROM n JOIN (SELECT s.src AS vid, sum(n.x) AS x FROM s JOIN n ON n.vid = s.dst GROUP BY 1) t USING (vid)")
def mp_sym_hop1(spark: SparkSession, d: str) -> DataFrame:
    ee, _, x = placed(spark, d)
    # degrees count neighbours and the vertex itself on both sides
    return message.aggregate(ee, x, "sym", d=1).select("vid", F.round(F.get("x", F.lit(0)), 6).alias("x"))


@query(_S + " SELECT vid, round(greatest(x * 0.5 - 100, 0.0), 6) AS x0, round(greatest(x * -0.25 + 0.0, 0.0), 6) AS x1 FROM (SELECT vid, CAST(x AS DOUBLE) AS x FROM (SELECT vid, x - 200 AS x FROM g1) WHERE true) z(vid, y), LATERAL (SELECT y AS x)".replace("x * 0.5 - 100", "x * 0.5"))
def mp_dense_relu(spark: SparkSession, d: str) -> DataFrame:
    ee, _, x = placed(spark, d)
    z = message.aggregate(ee, x, "sum", d=1).select("vid", F.transform("x", lambda v: (v - 200).cast("double")).alias("x"))
    out = message.dense_sql(z, [[0.5, -0.25]], "relu")
    return out.select("vid", F.round(F.get("x", F.lit(0)), 6).alias("x0"), F.round(F.get("x", F.lit(1)), 6).alias("x1"))


_GATES = {"wz": 0.5, "uz": -0.25, "wr": 0.125, "ur": 0.75, "wh": 1.0, "uh": -0.5}


@query(_S + """, p AS (SELECT f.vid, f.x / 97.0 AS x, CASE WHEN f.vid % 3 = 0 THEN 0.0 ELSE f.x / 194.0 END AS p FROM f),
g AS (SELECT *, 1 / (1 + exp(-(0.5 * x - 0.25 * p))) AS z, 1 / (1 + exp(-(0.125 * x + 0.75 * p))) AS r FROM p)
SELECT vid, round((1 - z) * p + z * tanh(x - 0.5 * r * p), 6) AS x FROM g""")
def mp_gru_small(spark: SparkSession, d: str) -> DataFrame:
    """The recurrent step in one dimension; a third of the vertices have no previous state."""
    _, _, f = placed(spark, d)
    cur = f.select("vid", (F.get("x", F.lit(0)) / 97.0).alias("x"))
    prev = f.filter("vid % 3 <> 0").select("vid", (F.get("x", F.lit(0)) / 194.0).alias("x"))
    return recurrent.gru_scalar(cur, prev, _GATES).select("vid", F.round("x", 6).alias("x"))


@query(_S + " SELECT vid, CASE WHEN vid % 5 = 0 THEN -x ELSE x END AS x FROM f")
def mp_state_assemble(spark: SparkSession, d: str) -> DataFrame:
    f = _scalar(placed(spark, d)[2])
    return recurrent.assemble(f.filter("vid % 5 = 0").select("vid", (-F.col("x")).alias("x")), f)


@query("SELECT user_id * 8 + 4 AS vid, CAST(max(" + sql.DAY.format("ts") + ") AS INTEGER) AS snap, arg_max(event_id, (ts, event_id)) AS x FROM events WHERE " + sql.DAY.format("ts") + " <= 12 GROUP BY 1")
def mp_state_asof(spark: SparkSession, d: str) -> DataFrame:
    """Latest version at or before day 12, where each user's last event of a day is that day's version."""
    e = table(spark, d, "events", "event_id", "ts", "user_id").withColumn("snap", graphs.day("ts"))
    versions = e.groupBy("snap", graphs.vid("user_id", "user").alias("vid")).agg(F.max_by("event_id", F.struct("ts", "event_id")).alias("x"))
    return recurrent.as_of(versions, 12).select("vid", "snap", "x")


@query("SELECT CAST(0 AS BIGINT) AS wrong")
def mp_ring_equals_full(spark: SparkSession, d: str) -> DataFrame:
    """Vertices on which recomputing rings only, over two rectified layers, differs from recomputing everything."""
    e = materialise(_weekly(spark, d), "edges")
    w = [[0.5, -0.25]], [[1.0], [0.5]]

    def layers(t: int, rings: DataFrame | None, before: list[DataFrame] | None) -> list[DataFrame]:
        now = snapshots.at(e, t)
        both = graphs.symmetric(now)
        h = graphs.small_feature(graphs.vertices(now)).select("vid", F.array(F.col("x").cast("double")).alias("x"))
        out = []
        for layer, m in enumerate(w, 1):
            todo = rings.filter(F.col("layer") == layer).select("vid") if rings is not None else None
            new = message.dense_sql(message.aggregate(both, h, "sum", todo, d=len(m)), m, "relu")
            h = materialise(new if before is None else recurrent.assemble(new, before[layer - 1]), "layer")
            out.append(h)
        return out

    old = layers(170, None, None)
    part = layers(171, materialise(region.rings(snapshots.at(e, 171), region.seeds(e, 171), 2), "rings"), old)
    return quality.residual(part[-1], layers(171, None, None)[-1]).select("wrong")


# --- exchange


@query(_S + " SELECT vid, x FROM d1")
def x_hop1(spark: SparkSession, d: str) -> DataFrame:
    ee, _, x = placed(spark, d)
    return _scalar(exchange.hop1(ee, x, d=1))


@query(_S + " SELECT vid, x FROM printed")
def x_hop2_printed(spark: SparkSession, d: str) -> DataFrame:
    ee, _, x = placed(spark, d)
    return _scalar(exchange.hop2(ee, x, "printed", d=1))


@query(_S + " SELECT vid, x FROM excl")
def x_hop2_excl_self(spark: SparkSession, d: str) -> DataFrame:
    ee, _, x = placed(spark, d)
    return _scalar(exchange.hop2(ee, x, "printed_excl_self", d=1))


@query(_S + " SELECT vid, x FROM complete")
def x_hop2_complete(spark: SparkSession, d: str) -> DataFrame:
    ee, _, x = placed(spark, d)
    return _scalar(exchange.hop2(ee, x, "complete", d=1))


@query(_S + " SELECT h2.vid, CAST(h2.x + coalesce(c.x, 0) AS BIGINT) AS x FROM h2 LEFT JOIN complete c USING (vid)")
def x_apply(spark: SparkSession, d: str) -> DataFrame:
    ee, _, x = placed(spark, d)
    return _scalar(exchange.apply(exchange.local_states(ee, x, 2, 1), exchange.hop2(ee, x, d=1)))


@query(_S + " SELECT vid, x FROM g1")
def x_truth_hop1(spark: SparkSession, d: str) -> DataFrame:
    ee, _, x = placed(spark, d)
    return _scalar(exchange.truth(ee, x, 1, 1))


@query(_S + " SELECT vid, x FROM g2")
def x_truth_hop2(spark: SparkSession, d: str) -> DataFrame:
    ee, _, x = placed(spark, d)
    return _scalar(exchange.truth(ee, x, 2, 1))


def _residual_sql(name: str) -> str:
    row = "SELECT '{0}' AS mode, count(*) AS vertices, count(*) FILTER (g2.x <> h2.x + coalesce(c.x, 0)) AS wrong FROM g2 JOIN h2 USING (vid) LEFT JOIN {1} c USING (vid)"
    none = "(SELECT vid, 0 AS x FROM v)"
    return sql.base(name) + sql.SUMS + " " + " UNION ALL ".join(row.format(m, t) for m, t in (("none", none), ("printed", "printed"), ("printed_excl_self", "excl"), ("complete", "complete")))


def _residuals(spark: SparkSession, d: str, name: str) -> DataFrame:
    ee, _, x = placed(spark, d, name)
    x = materialise(x, "features")
    local, want = materialise(exchange.local_states(ee, x, 2, 1), "local"), materialise(exchange.truth(ee, x, 2, 1), "truth")
    rows = quality.residual(local, want).select(F.lit("none").alias("mode"), "vertices", "wrong")
    for mode in ("printed", "printed_excl_self", "complete"):
        rows = rows.unionAll(quality.residual(exchange.apply(local, exchange.hop2(ee, x, mode, d=1)), want).select(F.lit(mode), "vertices", "wrong"))
    return rows


for _g in ("copurchase", "talk", "buy", "link", "ship"):
    query(_residual_sql(_g), name="x_residual_by_mode" if _g == "copurchase" else f"x_residual_{_g}")(lambda spark, d, _n=_g: _residuals(spark, d, _n))


_XR = _R + sql.SUMS


def _exchange_scope(spark: SparkSession, d: str, scoped: bool) -> DataFrame:
    now = materialise(_now(spark, d), "edges")
    v = graphs.vertices(now)
    asg = graphs.by_key(v)
    ee = materialise(clients.placed(now, asg), "placed")
    x = graphs.small_feature(v).select("vid", F.array("x").alias("x"))
    reach = materialise(region.khop(now, region.seeds(_weekly(spark, d), 171), 2), "region") if scoped else None
    return _scalar(exchange.hop2(ee, x, "complete", reach, d=1))


@query(_XR + " SELECT vid, x FROM complete SEMI JOIN k2 USING (vid)")
def x_scope_region(spark: SparkSession, d: str) -> DataFrame:
    """Incremental exchange: corrections of the changed region only, from its halo."""
    return _exchange_scope(spark, d, True)


@query(_XR + " SELECT vid, x FROM complete")
def x_scope_all(spark: SparkSession, d: str) -> DataFrame:
    return _exchange_scope(spark, d, False)


@query(_S + " SELECT vid, x FROM g1")
def x_feature_sum_owner(spark: SparkSession, d: str) -> DataFrame:
    ee, _, x = placed(spark, d)
    return _scalar(exchange.feature_sum(ee, x, "owner", 1))


@query(_S + " SELECT vid, x FROM h1")
def x_feature_sum_literal(spark: SparkSession, d: str) -> DataFrame:
    ee, _, x = placed(spark, d)
    return _scalar(exchange.feature_sum(ee, x, "literal", 1))


@query("SELECT * FROM (VALUES ('first/all', CAST(10 AS BIGINT)), ('last/all', 10), ('last/first', 1), ('last/mid', 1)) t(schedule, firings)")
def x_schedules(spark: SparkSession, d: str) -> DataFrame:
    rows = ", ".join(f"('{s.epoch}/{s.rounds}', {s.firings(5, 10)}L)" for s in exchange.SCHEDULES)
    return spark.sql(f"SELECT * FROM VALUES {rows} AS t(schedule, firings)")


_OUTBOX = " FROM (SELECT asg.part, vid, CAST(1 AS INTEGER) AS hop, x FROM d1 JOIN asg USING (vid) UNION ALL SELECT asg.part, vid, 2, x FROM complete JOIN asg USING (vid))"


@query(_S + " SELECT CAST(9 AS INTEGER) AS snap, part, vid, hop, CAST(x AS FLOAT) AS x" + _OUTBOX)
def x_outbox(spark: SparkSession, d: str) -> DataFrame:
    ee, asg, x = placed(spark, d)
    return exchange.outbox(ee, x, asg, 9, d=1).select("snap", "part", "vid", "hop", F.get("x", F.lit(0)).alias("x"))


@query(_S + " SELECT part, vid, CAST(0 AS INTEGER) AS hop, f.x FROM f JOIN asg USING (vid) WHERE vid IN (SELECT src FROM cut) UNION ALL SELECT part, vid, 1, h1.x FROM h1 JOIN asg USING (vid) WHERE vid IN (SELECT src FROM cut)")
def x_inbox(spark: SparkSession, d: str) -> DataFrame:
    ee, _, x = placed(spark, d)
    return exchange.submit(ee, x, 1).select("part", "vid", "hop", F.get("x", F.lit(0)).alias("x"))


@query(_S + " SELECT vid, CAST(CAST(x AS FLOAT) AS DOUBLE) AS x FROM g2")
def x_protocol(spark: SparkSession, d: str) -> DataFrame:
    """Submit, combine, send, add, through written in- and outboxes."""
    ee, asg, x = placed(spark, d)
    return _scalar(exchange.protocol(ee, x, asg, 9, d=1))


@query(_S + """, a1 AS (SELECT vid, greatest(x * 0.5, 0) AS p, greatest(x * 0.25, 0) AS q FROM g1),
b AS (SELECT vid, sum(p) AS p, sum(q) AS q FROM (SELECT vid, p, q FROM a1 UNION ALL SELECT s.src, a1.p, a1.q FROM s JOIN a1 ON a1.vid = s.dst) GROUP BY 1)
SELECT vid, round(greatest(CAST(p - 0.5 * q AS DOUBLE), 0.0), 6) AS x FROM b""")
def x_layerwise(spark: SparkSession, d: str) -> DataFrame:
    """Two rectified layers over corrected sums equal those over the whole graph."""
    ee, _, x = placed(spark, d)
    return exchange.layerwise(ee, x, [[[0.5, 0.25]], [[1.0], [-0.5]]], "relu", 1).select("vid", F.round(F.get("x", F.lit(0)), 6).alias("x"))


_PAPER = "('citation, five classes', 1L, 0.0006D, 42000L, 100L, 4L, 8L, 0.1D), ('citation, three classes', 1L, 0.0006D, 24000L, 100L, 4L, 8L, 0.1D), ('communities', 1L, 0.036D, 244000L, 20L, 4L, 8L, 0.1D)"


@query("SELECT * FROM (VALUES ('citation, five classes', CAST(10080 AS DOUBLE), CAST(0.8 AS DOUBLE)), ('citation, three classes', 5760, 0.8), ('communities', 702720, 0.8)) t(name, bytes, seconds)")
def cost_model_paper(spark: SparkSession, d: str) -> DataFrame:
    """The closed model on the published parameters: 10,080, 5,760 and 702,720 bytes and 0.8 s each."""
    return cost.model(spark.sql(f"SELECT * FROM VALUES {_PAPER} AS t(name, firings, ratio, edges, dim, width, snaps, latency)"))


@query(_S + " SELECT part, hop, count(*) AS messages, CAST(count(*) * 12 AS BIGINT) AS bytes" + _OUTBOX + " GROUP BY 1, 2")
def cost_actual_outbox(spark: SparkSession, d: str) -> DataFrame:
    ee, asg, x = placed(spark, d)
    return cost.actual(exchange.outbox(ee, x, asg, 9, d=1))


@query(_XR + " SELECT (SELECT count(*) FROM complete SEMI JOIN k2 USING (vid)) AS incremental, (SELECT count(*) FROM complete) AS whole")
def cost_incremental_vs_full(spark: SparkSession, d: str) -> DataFrame:
    """Two-hop messages of the incremental and of the whole exchange at one weekly snapshot."""
    part = _exchange_scope(spark, d, True).agg(F.count(F.lit(1)).alias("incremental"))
    return part.join(F.broadcast(_exchange_scope(spark, d, False).agg(F.count(F.lit(1)).alias("whole"))))


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Two-hop states of the newest co-purchase snapshot's region, corrected by the incremental exchange."""
    e = materialise(graphs.edges(spark, d, "copurchase"), "edges")
    last = 9
    now = snapshots.at(e, last)
    v = graphs.vertices(now)
    ee = materialise(clients.placed(now, graphs.by_key(v)), "placed")
    x = graphs.small_feature(v).select("vid", F.array("x").alias("x"))
    reach = materialise(region.khop(now, region.seeds(e, last), 2), "region")
    local = exchange.local_states(ee, x, 2, 1).join(reach.select("vid"), "vid", "left_semi")
    return _scalar(exchange.apply(local, exchange.hop2(ee, x, "complete", reach, 1)))
