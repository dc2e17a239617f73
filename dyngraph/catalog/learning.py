"""Queries: evaluation measures, averaging, training runs, rival models."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import evaluate
from ..functions.vectors import dot
from ..operators import clients, encoder, exchange, federate, snapshots, trainer
from ..sources import graphs
from ..sources.tables import materialise, table
from . import sql
from .partitions import M, segments, statuses
from .registry import query
from .structure import placed

# Scores for the ranking measures: each user's event types ranked by how often the user has them; positives are types
# with a mean value over 50. All values are small integers, so both engines agree on every tie.
_SCORES = "sc AS MATERIALIZED (SELECT user_id AS query, CAST(ascii(event_type) AS BIGINT) * 1000 + length(event_type) AS cand, CAST(count(*) AS DOUBLE) AS score, CAST(max(event_id) % 2 AS INTEGER) AS y FROM events GROUP BY user_id, event_type)"


def scores(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events", "event_id", "user_id", "event_type")
    g = e.groupBy(F.col("user_id").alias("query"), "event_type").agg(F.count(F.lit(1)).cast("double").alias("score"), (F.max("event_id") % 2).cast("int").alias("y"))
    return g.select("query", (F.ascii("event_type").cast("long") * 1000 + F.length("event_type")).alias("cand"), "score", "y")


_RANKED = f"WITH {_SCORES}, r AS (SELECT *, row_number() OVER (PARTITION BY query ORDER BY score DESC, cand) AS rank, sum(y) OVER (PARTITION BY query ORDER BY score DESC, cand) AS hits FROM sc)"


@query(_RANKED + " SELECT count(*) AS queries, round(avg(rr), 6) AS mrr FROM (SELECT query, 1 / min(rank) AS rr FROM r WHERE y = 1 GROUP BY 1)")
def ev_mrr(spark: SparkSession, d: str) -> DataFrame:
    return evaluate.mrr(scores(spark, d))


for _t, _e in (("optimistic", "low"), ("pessimistic", "low + tied - 1"), ("average", "low + (tied - 1) / 2.0")):
    query(f"WITH {_SCORES}, r AS (SELECT query, y, rank() OVER (PARTITION BY query ORDER BY score DESC) AS low, count(*) OVER (PARTITION BY query, score) AS tied FROM sc) SELECT count(*) AS queries, round(avg(rr), 6) AS mrr FROM (SELECT query, 1 / min({_e}) AS rr FROM r WHERE y = 1 GROUP BY 1)", name=f"ev_mrr_{_t}")(lambda spark, d, _t=_t: evaluate.mrr(scores(spark, d), _t))


@query(_RANKED + " SELECT count(*) AS queries, round(avg(ap), 6) AS map FROM (SELECT query, avg(hits / rank) AS ap FROM r WHERE y = 1 GROUP BY 1)")
def ev_map_query(spark: SparkSession, d: str) -> DataFrame:
    return evaluate.map_by_query(scores(spark, d))


@query(f"WITH {_SCORES}, r AS (SELECT y, row_number() OVER w AS rank, sum(y) OVER (ORDER BY score DESC, query, cand ROWS UNBOUNDED PRECEDING) AS hits FROM sc WINDOW w AS (ORDER BY score DESC, query, cand)) SELECT count(*) AS positives, round(avg(hits / rank), 6) AS map FROM r WHERE y = 1")
def ev_map_global(spark: SparkSession, d: str) -> DataFrame:
    return evaluate.global_precision(scores(spark, d))


@query(f"WITH {_SCORES} SELECT count(*) AS n, round(avg(CAST(CAST(score - 12 >= 0 AS INTEGER) = y AS INTEGER)), 6) AS accuracy FROM sc")
def ev_accuracy(spark: SparkSession, d: str) -> DataFrame:
    return evaluate.accuracy(scores(spark, d).withColumn("score", F.col("score") - 12))


_PRED = f"SELECT y, CAST((vid // 8) % 6 AS INTEGER) AS yhat FROM ({sql.SEGMENT})"
_F1 = f"""WITH p AS MATERIALIZED ({_PRED}), c AS (SELECT y AS c FROM p UNION SELECT yhat FROM p),
f AS (SELECT c.c, count(*) FILTER (y = c.c AND yhat = c.c) AS tp, count(*) FILTER (yhat = c.c) AS np, count(*) FILTER (y = c.c) AS nt FROM c CROSS JOIN p GROUP BY 1), g AS (SELECT *, 2 * tp / (np + nt) AS f FROM f)"""


def predictions(spark: SparkSession, d: str) -> DataFrame:
    """Six guessed classes against five true ones, so that one is never right."""
    return segments(spark, d).select("y", (graphs.key_of("vid") % 6).cast("int").alias("yhat"))


for _a, _e in (("macro", "avg(f)"), ("micro", "sum(tp) / sum(nt)"), ("weighted", "sum(f * nt) / sum(nt)")):
    query(_F1 + f" SELECT round({_e}, 6) AS f1 FROM g", name=f"ev_f1_{_a}")(lambda spark, d, _a=_a: evaluate.f1(predictions(spark, d), _a))

_MATRIX = "('a', 1, 1, 0.9D), ('a', 1, 2, 0.8D), ('a', 1, 3, 0.6D), ('a', 2, 2, 0.7D), ('a', 2, 3, 0.75D), ('a', 3, 3, 0.5D)"


def _matrix(spark: SparkSession) -> DataFrame:
    return spark.sql(f"SELECT task, after_task, score FROM VALUES {_MATRIX} AS t(name, task, after_task, score)")


@query("SELECT CAST(2 AS BIGINT) AS tasks, CAST(0.125 AS DOUBLE) AS forgetting")
def ev_forgetting(spark: SparkSession, d: str) -> DataFrame:
    """Fixed matrix: ((0.9 - 0.6) + (0.7 - 0.75)) / 2."""
    return evaluate.forgetting(_matrix(spark))


@query("SELECT CAST(2 AS BIGINT) AS tasks, CAST(0.125 AS DOUBLE) AS forgetting")
def ev_forgetting_peak(spark: SparkSession, d: str) -> DataFrame:
    return evaluate.forgetting(_matrix(spark), peak=True)


@query("SELECT * FROM (VALUES ('F1, five classes', CAST(0.7243 AS DOUBLE), CAST(0.7269 AS DOUBLE), CAST(0.00359 AS DOUBLE)), ('F1, three classes', 0.5836, 0.6616, 0.133653), ('F1, communities', 0.2733, 0.2834, 0.036956)) t(measure, best, ours, gain)")
def ev_improvement(spark: SparkSession, d: str) -> DataFrame:
    """Relative gains recomputed from the published means."""
    rows = "('F1, five classes','rival',0.7243D),('F1, five classes','ours',0.7269D),('F1, three classes','rival',0.5836D),('F1, three classes','ours',0.6616D),('F1, communities','rival',0.2733D),('F1, communities','weaker',0.2506D),('F1, communities','ours',0.2834D)"
    return evaluate.improvement(spark.sql(f"SELECT * FROM VALUES {rows} AS t(measure, method, value)"), "ours").withColumn("gain", F.round("gain", 6))


@query("SELECT event_type, count(*) AS n, round(avg(value), 6) AS mean, round(stddev_samp(value), 6) AS std FROM events GROUP BY 1")
def ev_mean_std(spark: SparkSession, d: str) -> DataFrame:
    return evaluate.summarise(table(spark, d, "events", "event_type", "value"), "event_type", "value")


@query("SELECT CAST(t AS INTEGER) AS train, CAST(t + 1 AS INTEGER) AS validate, CAST(t + 2 AS INTEGER) AS test FROM range(8) r(t)")
def ev_live_update_folds(spark: SparkSession, d: str) -> DataFrame:
    return evaluate.live_update_folds(9, spark)


_DOT = sql.base("copurchase") + ", h AS (SELECT vid, vid % 7 - 3 AS p, vid % 11 - 5 AS q FROM v)"


def _states(spark: SparkSession, d: str) -> DataFrame:
    v = graphs.vertices(graphs.edges(spark, d, "copurchase"))
    return v.select("vid", F.array(F.col("vid") % 7 - 3, F.col("vid") % 11 - 5).alias("x"))


@query(_DOT + " SELECT a AS u, b AS v, CAST(x.p * y.p + x.q * y.q AS DOUBLE) AS score FROM e JOIN h x ON x.vid = a JOIN h y ON y.vid = b WHERE first = 9")
def ev_dot_scores(spark: SparkSession, d: str) -> DataFrame:
    pairs = snapshots.delta(graphs.edges(spark, d, "copurchase"), 9).select(F.col("a").alias("u"), F.col("b").alias("v"))
    return evaluate.dot_scores(_states(spark, d), pairs).select("u", "v", "score")


_MD5 = "CAST(('0x' || substr(md5({0}), 1, 13)) AS BIGINT)"
_RANKS = ", rk AS MATERIALIZED (SELECT vid, part, row_number() OVER (PARTITION BY part ORDER BY vid) - 1 AS rank, count(*) OVER (PARTITION BY part) AS size FROM asg), sz AS (SELECT DISTINCT part, size FROM rk)"


@query(sql.base("copurchase") + _RANKS + f""", pos AS (SELECT src AS u, dst AS v FROM ee WHERE src < dst AND pu = pv AND first = 9),
c AS (SELECT p.u, p.v, k.k, rk.vid AS neg FROM pos p JOIN asg ON asg.vid = p.u JOIN sz USING (part) CROSS JOIN range(1, 9) k(k) JOIN rk ON rk.part = asg.part AND rk.rank = {_MD5.format("'neg:' || p.u || ':' || p.v || ':' || k.k")} % sz.size)
SELECT u, v, arg_min(neg, k) AS neg FROM c WHERE neg <> u AND NOT EXISTS (SELECT 1 FROM s WHERE s.src = c.u AND s.dst = c.neg) GROUP BY 1, 2""")
def ev_negatives(spark: SparkSession, d: str) -> DataFrame:
    ee, asg, _ = placed(spark, d)
    pos = clients.local(ee).filter("src < dst and first = 9").select(F.col("src").alias("u"), F.col("dst").alias("v"))
    return evaluate.negatives(pos, asg, ee, "neg")


_CUT = sql.base("copurchase", where="first <= 4") + _RANKS + f""", pos AS MATERIALIZED (SELECT src AS u, dst AS v FROM ee WHERE src < dst AND pu <> pv), n AS (SELECT count(*) AS n FROM pos),
dr AS (SELECT id, {_MD5.format("'cut:p:' || id")} % {M} AS p FROM n, LATERAL (SELECT unnest(range(2 * n.n)) AS id)),
dq AS (SELECT id, p, (p + 1 + {_MD5.format("'cut:q:' || id")} % {M - 1}) % {M} AS q FROM dr),
dv AS (SELECT dq.id, a.vid AS u0, b.vid AS v0 FROM dq JOIN sz sp ON sp.part = dq.p JOIN sz sq ON sq.part = dq.q JOIN rk a ON a.part = dq.p AND a.rank = {_MD5.format("'cut:ru:' || dq.id")} % sp.size JOIN rk b ON b.part = dq.q AND b.rank = {_MD5.format("'cut:rv:' || dq.id")} % sq.size),
dd AS (SELECT least(u0, v0) AS u, greatest(u0, v0) AS v, min(id) AS id FROM dv GROUP BY 1, 2),
ng AS (SELECT u, v, row_number() OVER (ORDER BY id) AS r FROM dd WHERE NOT EXISTS (SELECT 1 FROM e WHERE e.a = dd.u AND e.b = dd.v))
SELECT u, v, CAST(1 AS INTEGER) AS y FROM pos UNION ALL SELECT u, v, 0 FROM ng, n WHERE r <= n.n"""


@query(_CUT)
def ev_cut_edge_task(spark: SparkSession, d: str) -> DataFrame:
    ee, asg, _ = placed(spark, d, t=4)
    return evaluate.cut_edge_task(ee, asg, "cut", M)


_BIAS = sql.base("trade", where="first <= 40") + f""", nx AS MATERIALIZED (SELECT DISTINCT a AS query, b AS cand FROM ({sql.edges('trade')}) WHERE first = 41 AND a % 8 = 0 AND (a // 8) % 100 = 0),
q AS (SELECT DISTINCT query FROM nx), cd AS (SELECT vid AS cand FROM v WHERE vid % 8 = 2),
sc AS MATERIALIZED (SELECT query, cand, CAST(max(y) AS INTEGER) AS y FROM (SELECT query, cand, 1 AS y FROM nx UNION ALL SELECT query, cand, 0 FROM q CROSS JOIN cd) GROUP BY 1, 2),
r AS (SELECT query, y, row_number() OVER w AS rank, sum(y) OVER w AS hits FROM sc LEFT JOIN d ON d.vid = sc.cand WINDOW w AS (PARTITION BY query ORDER BY coalesce(deg, 0) DESC, cand))
SELECT round(avg(rr), 6) AS mrr, round(avg(ap), 6) AS map FROM (SELECT query, 1 / min(rank) AS rr, avg(hits / rank) AS ap FROM r WHERE y = 1 GROUP BY 1)"""


@query(_BIAS)
def ev_degree_bias(spark: SparkSession, d: str) -> DataFrame:
    """Ranking all parts for the customers whose key is divisible by 100 by degree alone: the probe that tells mean
    reciprocal rank from mean precision."""
    e = materialise(graphs.edges(spark, d, "trade"), "edges")
    past = snapshots.at(e, 40)
    pos = e.filter("first = 41 and a % 8 = 0 and (a div 8) % 100 = 0").select(F.col("a").alias("query"), F.col("b").alias("cand")).distinct()
    every = graphs.vertices(past).filter(F.col("vid") % 8 == 2).select(F.col("vid").alias("cand"))
    grid = pos.select("query").distinct().join(F.broadcast(every))  # a stated candidate set for each query
    labelled = pos.withColumn("y", F.lit(1)).unionAll(grid.withColumn("y", F.lit(0))).groupBy("query", "cand").agg(F.max("y").alias("y"))
    sc = materialise(evaluate.degree_scores(graphs.symmetric(past), labelled), "scores")
    return evaluate.mrr(sc).select("mrr").join(F.broadcast(evaluate.map_by_query(sc).select("map")))


# --- averaging

_PARAMS = "('0','w',array(1D,2D)),('1','w',array(3D,6D)),('2','w',array(5D,4D)),('0','b',array(1D)),('1','b',array(2D)),('2','b',array(6D))"


@query("SELECT name, CAST(idx AS INTEGER) AS idx, CAST(sum(v * w) / sum(w) AS DOUBLE) AS value FROM (VALUES ('w', 0, 1, 5), ('w', 0, 3, 2), ('w', 0, 5, 1), ('w', 1, 2, 5), ('w', 1, 6, 2), ('w', 1, 4, 1), ('b', 0, 1, 5), ('b', 0, 2, 2), ('b', 0, 6, 1)) t(name, idx, v, w) GROUP BY 1, 2")
def fed_average(spark: SparkSession, d: str) -> DataFrame:
    """Weights 5, 2 and 1; a client without vertices would be left out."""
    params = spark.sql(f"SELECT * FROM VALUES {_PARAMS} AS t(client, name, data)")
    weights = spark.sql("SELECT * FROM VALUES ('0', 5D), ('1', 2D), ('2', 1D) AS t(client, weight)")
    return federate.average(params, weights)


@query("SELECT label AS y, CAST(i - 1 AS INTEGER) AS dim, round(avg(CAST(embedding[i] AS DOUBLE)), 5) AS value FROM embeddings, range(1, 65) r(i) GROUP BY 1, 2")
def fed_prototypes(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "embeddings", "vec_id", "embedding", "label")
    out = federate.prototypes(e.select(F.col("vec_id").alias("vid"), F.col("embedding").cast("array<double>").alias("x")), e.select(F.col("vec_id").alias("vid"), F.col("label").alias("y")))
    return out.select("y", "dim", F.round("value", 5).alias("value"))


# --- training; weights come from fixed seeds, so a run repeats, but floats are engine-bound and have no SQL


def _features(spark: SparkSession, d: str, e: DataFrame) -> DataFrame:
    """Degree-free raw features of customers: balance and nation."""
    c = table(spark, d, "customer", "c_custkey", "c_acctbal", "c_nationkey")
    return c.select(graphs.vid("c_custkey", "customer").alias("vid"), F.array("c_acctbal", F.col("c_nationkey").cast("double"), F.lit(1.0)).alias("x"))


BASE = trainer.Settings(rounds=2, epochs=3, hidden=6)


def trained(spark: SparkSession, d: str, s: trainer.Settings, classes: int = 5, last: int = 3, clients_: int = M) -> DataFrame:
    """(snap, round, loss, exchanged, clients) of a live-update run on co-purchases."""
    e = materialise(graphs.edges(spark, d, "copurchase"), "edges")
    asg = materialise(graphs.by_key(graphs.vertices(e), clients_), "assignment")
    _, log, _ = trainer.live_update(e, last, _features(spark, d, e), segments(spark, d) if s.task == "class" else None, asg, s, classes, first=last - 1)
    rows = ", ".join(f"({r['snap']}, {r['round']}, {r['loss']:.6f}D, {str(r['exchanged']).lower()}, {r['clients']})" for r in log)
    return spark.sql(f"SELECT * FROM VALUES {rows} AS t(snap, round, loss, exchanged, clients)")


RUNS = {
    "fed_train_link": BASE,
    "fed_train_class": replace(BASE, task="class"),
    "fed_two_hop": replace(BASE, task="class", hops=2),
    "fed_schedule_first_epoch": replace(BASE, task="class", schedule=exchange.Schedule("first", "all")),
    "fed_no_exchange": replace(BASE, scheme="none"),
    "fed_feature_sum": replace(BASE, scheme="feature_sum"),
    "fed_full_retrain": replace(BASE, mode="full", schedule=exchange.Schedule("last", "all")),
    "rival_state_gru": replace(BASE, mode="full", scheme="none"),
    "rival_weight_evolve_h": replace(BASE, mode="full", scheme="none", evolve="h", cell=""),
    "rival_weight_evolve_o": replace(BASE, mode="full", scheme="none", evolve="o", cell=""),
    "rival_conv_recurrent": replace(BASE, mode="full", scheme="none", layers=1),
    "rival_conv_plain": replace(BASE, mode="full", scheme="none", layers=1, cell=""),
    "rival_ring_average": replace(BASE, task="class", scheme="none", averaging="ring"),
    "rival_average_evolve": replace(BASE, task="class", scheme="none", evolve="o", cell="", mode="full"),
    "rival_disjoint_federated": replace(BASE, task="class", scheme="none", mode="full"),
    "rival_replay": replace(BASE, task="class", replay=0.1),
    "rival_importance": replace(BASE, task="class", importance=0.5),
    "rival_influence": replace(BASE, task="class", influence=True),
    "rival_neighbour_gen": replace(BASE, task="class", scheme="none", generate=True),
}
_CENTRAL = {"rival_state_gru", "rival_weight_evolve_h", "rival_weight_evolve_o", "rival_conv_recurrent", "rival_conv_plain"}
for _n, _s in RUNS.items():
    query(name=_n)(lambda spark, d, _n=_n, _s=_s: trained(spark, d, _s, clients_=1 if _n in _CENTRAL else M))


@query()
def rival_prototypes(spark: SparkSession, d: str) -> DataFrame:
    """Prototype aggregation: class means of local states; each customer is given the class of its nearest mean."""
    e = materialise(snapshots.at(graphs.edges(spark, d, "copurchase"), 3), "edges")
    asg = materialise(graphs.by_key(graphs.vertices(e), M), "assignment")
    y = segments(spark, d)
    s = replace(BASE, task="class", scheme="none", mode="full")
    states, _, _ = trainer.live_update(e, 3, _features(spark, d, e), y, asg, s, 5, first=3)
    h = states[-1]
    means = federate.prototypes(h, y).groupBy("y").agg(F.transform(F.array_sort(F.collect_list(F.struct("dim", "value"))), lambda p: p["value"]).alias("m"))
    near = h.join(F.broadcast(means)).withColumn("far", dot(F.zip_with("x", "m", lambda a, b: a - b), F.zip_with("x", "m", lambda a, b: a - b)))
    pred = near.groupBy("vid").agg(F.min_by("y", F.struct("far", "y")).alias("yhat")).join(y, "vid")
    return evaluate.f1(pred.select("y", "yhat"))


@query()
def train_classify_f1(spark: SparkSession, d: str) -> DataFrame:
    """Macro F1 of a whole run on orders by status (three classes) in the graph of customers and orders."""
    e = materialise(snapshots.at(graphs.edges(spark, d, "buy"), 3), "edges")
    o = table(spark, d, "orders", "o_orderkey", "o_totalprice").select(graphs.vid("o_orderkey", "order").alias("vid"), F.array("o_totalprice", F.lit(1.0), F.lit(0.0)).alias("x"))
    f = o.unionAll(_features(spark, d, e))
    asg = materialise(graphs.by_key(graphs.vertices(e), M), "assignment")
    y = statuses(spark, d)
    states, _, m = trainer.live_update(e, 3, f, y, asg, replace(BASE, task="class"), 3, first=2)
    return evaluate.f1(_held_out(trainer.classify(states[-1], m).join(y, "vid")).select("y", "yhat"))


def _held_out(df: DataFrame) -> DataFrame:
    """The vertices that ``trainer.fit`` leaves out of training."""
    return df.filter(F.pmod(F.xxhash64("vid"), F.lit(10)) >= 7)


def _ranked(e: DataFrame, h: DataFrame, t: int) -> DataFrame:
    """mrr, map and accuracy of the links that are new at snapshot t, by dot products of the states h: every vertex that
    gets a link is a query against all vertices before t."""
    new = snapshots.delta(e, t).select("a", "b")
    pos = new.unionAll(new.select("b", "a")).toDF("query", "cand")
    return evaluate.link_measures(h, pos, graphs.vertices(snapshots.at(e, t - 1)))


def _stacked(rows: list[DataFrame]) -> DataFrame:
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out


@query()
def study_link_models(spark: SparkSession, d: str) -> DataFrame:
    """Live update: each model is trained up to snapshot 6, validated on the links of 7 and tested on those of 8."""
    e = materialise(graphs.edges(spark, d, "copurchase"), "edges")
    f, every, held = _features(spark, d, e), materialise(graphs.vertices(e), "vertices"), trainer.Held()
    asg = {m: materialise(graphs.by_key(every, m), "assignment") for m in (1, M)}

    def run(name: str) -> list[DataFrame]:
        states, _, _ = trainer.live_update(e, 6, f, None, asg[1 if name in _CENTRAL else M], RUNS[name], 2, first=5, held=held)
        return [_ranked(e, states[-1], t).select(F.lit(name).alias("model"), F.lit(role).alias("role"), "*") for role, t in (("validate", 7), ("test", 8))]

    names = ("fed_train_link", "fed_no_exchange", "fed_feature_sum", "rival_conv_plain", "rival_conv_recurrent", "rival_weight_evolve_o")
    with ThreadPoolExecutor(3) as pool:  # most jobs of a run are too short to fill the cores
        return _stacked([r for rows in pool.map(run, names) for r in rows])


def study_class_models(spark: SparkSession, d: str) -> DataFrame:
    """F1 of held-out customers at snapshot 8 by model, exchange schedule and hops, with the exchanges that took place."""
    e = materialise(graphs.edges(spark, d, "copurchase"), "edges")
    asg = materialise(graphs.by_key(graphs.vertices(e), M), "assignment")
    f, y, out = _features(spark, d, e), materialise(segments(spark, d), "labels"), []
    base = RUNS["fed_train_class"]
    runs = {f"schedule_{x.epoch}_{x.rounds}": replace(base, schedule=x) for x in exchange.SCHEDULES}
    runs |= {"two_hop": replace(base, hops=2), "no_exchange": replace(base, scheme="none")} | {n: RUNS[n] for n in ("rival_disjoint_federated", "rival_ring_average", "rival_importance")}
    for name, s in runs.items():
        states, log, m = trainer.live_update(e, 8, f, y, asg, s, 5, first=7)
        found = evaluate.f1(_held_out(trainer.classify(states[-1], m).join(y, "vid")).select("y", "yhat"))
        out.append(found.select(F.lit(name).alias("model"), F.lit(sum(r["exchanged"] for r in log)).alias("exchanges"), "*"))
    return _stacked(out)


@query()
def train_link_ranking(spark: SparkSession, d: str) -> DataFrame:
    """Reciprocal rank and precision of next-snapshot links after a run: all customers that get a link are queries against
    all customers."""
    e = materialise(graphs.edges(spark, d, "copurchase"), "edges")
    asg = materialise(graphs.by_key(graphs.vertices(e), M), "assignment")
    states, _, _ = trainer.live_update(e, 3, _features(spark, d, e), None, asg, BASE, 2, first=2)
    return _ranked(e, states[-1], 4)


@query()
def encoder_recent_pairs(spark: SparkSession, d: str) -> DataFrame:
    """Pluggable continuous-time encoder: scores of pairs of users from their most recent partners."""
    ev = table(spark, d, "events", "event_id", "ts", "user_id", "props").select(
        graphs.vid("user_id", "user").alias("u"), graphs.vid(F.get_json_object("props", "$.k"), "property").alias("v"), "ts", "event_id"
    )
    return encoder.scores(ev, cut="2024-01-21", recent=8)
