"""Queries: the partitioner's steps, its rivals, partition measures, privacy checks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import privacy, quality
from ..operators import clients, exchange, message, partition, partition_rivals, primitives, snapshots
from ..sources import graphs
from ..sources.tables import materialise, table
from . import sql
from .registry import query
from .structure import _scalar, placed

M = 4


def segments(spark: SparkSession, d: str) -> DataFrame:
    """Customers by market segment, 0 to 4 in order of name."""
    c = table(spark, d, "customer", "c_custkey", "c_mktsegment")
    codes = c.select("c_mktsegment").distinct().withColumn("y", (F.row_number().over(Window.orderBy("c_mktsegment")) - 1).cast("int"))  # a few classes
    return c.join(F.broadcast(codes), "c_mktsegment").select(graphs.vid("c_custkey", "customer").alias("vid"), "y")


def statuses(spark: SparkSession, d: str) -> DataFrame:
    """Orders by status, 0 to 2 in order of name."""
    o = table(spark, d, "orders", "o_orderkey", "o_orderstatus")
    codes = o.select("o_orderstatus").distinct().withColumn("y", (F.row_number().over(Window.orderBy("o_orderstatus")) - 1).cast("int"))
    return o.join(F.broadcast(codes), "o_orderstatus").select(graphs.vid("o_orderkey", "order").alias("vid"), "y")


# Old vertices: those present at snapshot 8 under key modulo 4; new ones come at 9.
_P = sql.base("copurchase") + f""",
seg AS MATERIALIZED ({sql.SEGMENT}),
arr AS MATERIALIZED (SELECT src AS vid, min(first) AS first FROM s GROUP BY 1),
old AS MATERIALIZED (SELECT asg.vid, asg.part FROM asg JOIN arr USING (vid) WHERE arr.first <= 3),
fresh AS MATERIALIZED (SELECT vid FROM arr WHERE first > 3),
vol AS MATERIALIZED (SELECT CAST(p.part AS INTEGER) AS part, CAST(coalesce(sum(d.deg), 0) AS BIGINT) AS vol FROM range({M}) p(part) LEFT JOIN old ON old.part = p.part LEFT JOIN d ON d.vid = old.vid GROUP BY 1),
votes AS MATERIALIZED (SELECT s.src AS vid, old.part, count(*) AS votes FROM s SEMI JOIN fresh ON s.src = fresh.vid JOIN old ON old.vid = s.dst GROUP BY 1, 2),
n AS MATERIALIZED (SELECT old.part, seg.y, count(*) AS n FROM old JOIN seg USING (vid) GROUP BY 1, 2),
ldiv AS MATERIALIZED (SELECT CAST(p.part AS INTEGER) AS part, y.y, 1 - coalesce(n.n, 0) / (coalesce(z.size, 0) + 1e-9) AS label_div FROM range({M}) p(part) CROSS JOIN (SELECT DISTINCT y FROM seg) y LEFT JOIN n ON n.part = p.part AND n.y = y.y LEFT JOIN (SELECT part, sum(n) AS size FROM n GROUP BY 1) z ON z.part = p.part),
bal AS MATERIALIZED (SELECT part, 1 - vol / (SELECT greatest(sum(vol), 1) FROM vol) AS balance FROM vol),
placed AS MATERIALIZED (SELECT vid, part FROM (SELECT votes.vid, votes.part, row_number() OVER (PARTITION BY votes.vid ORDER BY votes DESC, vol, votes.part) AS r FROM votes JOIN vol USING (part)) WHERE r = 1)"""


def _parts(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """Edges, both directions, old assignment, new vertices of the incremental tests."""
    e = materialise(graphs.edges(spark, d, "copurchase"), "edges")
    both = graphs.symmetric(e).select("src", "dst")
    arrived = snapshots.arrivals(e)
    old = graphs.by_key(arrived.filter("first <= 3"), M)
    return e, both, materialise(old, "old"), arrived.filter("first > 3").select("vid")


@query(sql.base("copurchase") + " SELECT CAST(greatest(2, least(100000, ceil(count(*) / 200))) AS INTEGER) AS clients, true AS valid FROM v")
def part_count_valid(spark: SparkSession, d: str) -> DataFrame:
    v = graphs.vertices(graphs.edges(spark, d, "copurchase"))
    m = partition.client_count(v.count(), target=200)
    return spark.range(1).select(F.lit(m).alias("clients"), F.lit(partition.is_valid(graphs.by_key(v, m), m, m)).alias("valid"))


_COMP = sql.base("reply") + ", w AS (SELECT vid, vid AS label FROM v UNION SELECT s.dst, w.label FROM w JOIN s ON s.src = w.vid), comp AS MATERIALIZED (SELECT vid, min(label) AS label FROM w GROUP BY 1)"


@query(_COMP + " SELECT vid, label FROM comp")
def part_components(spark: SparkSession, d: str) -> DataFrame:
    return primitives.components(graphs.edges(spark, d, "reply"))


@query(_COMP + """, rep AS (SELECT label, count(*) AS size, arg_max(vid, (deg, -vid)) AS rep FROM comp JOIN d USING (vid) GROUP BY 1)
SELECT least(rep, prev) AS a, greatest(rep, prev) AS b FROM (SELECT rep, lag(rep) OVER (ORDER BY size DESC, label) AS prev FROM rep) WHERE prev IS NOT NULL""")
def part_stitch(spark: SparkSession, d: str) -> DataFrame:
    e = materialise(graphs.edges(spark, d, "reply"), "edges")
    return partition.stitch(e, primitives.components(e))


@query(sql.base("copurchase") + " SELECT arg_max(vid, (deg, -vid)) AS vid FROM d")
def part_seed_first(spark: SparkSession, d: str) -> DataFrame:
    return partition.first_seed(graphs.edges(spark, d, "copurchase"))


@query(sql.base("docs") + ", w AS (SELECT 7 AS vid, 0 AS level UNION SELECT s.dst, w.level + 1 FROM w JOIN s ON s.src = w.vid WHERE w.level < 4) SELECT CAST(vid AS BIGINT) AS vid, CAST(min(level) AS INTEGER) AS level FROM w GROUP BY 1")
def part_bfs_levels(spark: SparkSession, d: str) -> DataFrame:
    """Distances from source 0 in the graph of documents and sources."""
    return primitives.levels(graphs.edges(spark, d, "docs"), spark.range(1).select(F.lit(7).cast("long").alias("vid")), 4)


@query(_P + " SELECT s.src AS vid, count(DISTINCT old.part) AS owners, CAST(min(old.part) AS INTEGER) AS part FROM s SEMI JOIN fresh ON s.src = fresh.vid JOIN old ON old.vid = s.dst GROUP BY 1")
def part_conflicts(spark: SparkSession, d: str) -> DataFrame:
    """One level of growth: owners that reach each open vertex; several owners are a conflict."""
    _, both, old, new = _parts(spark, d)
    return partition.reached(both, old, new)


@query(_P + " SELECT vid, part FROM placed")
def part_vote_cut(spark: SparkSession, d: str) -> DataFrame:
    _, both, old, new = _parts(spark, d)
    return partition.place(both, new, old, None, partition.Config(M))


@query(_P + " SELECT part, vol FROM vol")
def part_vote_balance(spark: SparkSession, d: str) -> DataFrame:
    """Edge volume of each client, by which balance-first placement deals vertices out."""
    _, both, old, _ = _parts(spark, d)
    return partition.volumes(both, old, M)


@query(_P + """, hv AS (SELECT fresh.vid, greatest(coalesce(deg, 1), 1) AS w FROM fresh LEFT JOIN d USING (vid)),
ln AS (SELECT vid, CAST(sum(w) OVER (ORDER BY vid % 1024, vid) - w AS BIGINT) AS at FROM hv), tt AS (SELECT CAST(sum(w) AS BIGINT) AS t FROM hv),
rk AS (SELECT part, CAST(vol AS BIGINT) AS vol, row_number() OVER o AS j, CAST(sum(vol) OVER o AS BIGINT) AS upto FROM vol WINDOW o AS (ORDER BY vol, part)),
us AS (SELECT rk.* FROM rk, tt WHERE j * vol - upto < t), tp AS (SELECT max(j) AS k, arg_max(upto, j) AS u FROM us),
iv AS (SELECT part, j, CAST(ceil((j * (t + u) - k * upto) / k) AS BIGINT) AS hi FROM us, tp, tt),
st AS (SELECT part, hi, coalesce(lag(hi) OVER (ORDER BY j), 0) AS lo FROM iv)
SELECT vid, part FROM ln JOIN st ON ln.at >= st.lo AND ln.at < st.hi""")
def part_place_balance(spark: SparkSession, d: str) -> DataFrame:
    """Balance-first placement of the new vertices: the lightest clients are filled to a common level of edge ends."""
    _, both, old, new = _parts(spark, d)
    return partition.place(both, new, old, None, partition.Config(M, primary="balance"))


@query(_P + " SELECT vid, part FROM (SELECT fresh.vid, ldiv.part, row_number() OVER (PARTITION BY fresh.vid ORDER BY label_div DESC, vol, ldiv.part) AS r FROM fresh JOIN seg USING (vid) JOIN ldiv ON ldiv.y = seg.y JOIN vol ON vol.part = ldiv.part) WHERE r = 1")
def part_vote_label(spark: SparkSession, d: str) -> DataFrame:
    _, both, old, new = _parts(spark, d)
    return partition.place(both, new, old, segments(spark, d), partition.Config(M, primary="label"))


@query(_P + " SELECT part, y, round(label_div, 6) AS label_div FROM ldiv")
def part_label_div(spark: SparkSession, d: str) -> DataFrame:
    return partition.label_diversity(_parts(spark, d)[2], segments(spark, d), M).select("part", "y", F.round("label_div", 6).alias("label_div"))


@query(_P + " SELECT part, round(balance, 6) AS balance FROM bal")
def part_balance(spark: SparkSession, d: str) -> DataFrame:
    _, both, old, _ = _parts(spark, d)
    return partition.balance(partition.volumes(both, old, M)).select("part", F.round("balance", 6).alias("balance"))


_REFINE = _P + """,
cv AS MATERIALIZED (SELECT s.src AS vid, asg.part, count(*) AS votes FROM s JOIN asg ON asg.vid = s.dst GROUP BY 1, 2),
cand AS MATERIALIZED (SELECT vid, part FROM cv UNION SELECT vid, part FROM asg),
avol AS MATERIALIZED (SELECT part, sum(deg) AS vol FROM asg JOIN d USING (vid) GROUP BY 1),
an AS MATERIALIZED (SELECT asg.part, seg.y, count(*) AS n FROM asg JOIN seg USING (vid) GROUP BY 1, 2),
adiv AS MATERIALIZED (SELECT p.part, y.y, 1 - coalesce(an.n, 0) / (z.size + 1e-9) AS label_div FROM (SELECT DISTINCT part FROM asg) p CROSS JOIN (SELECT DISTINCT y FROM seg) y LEFT JOIN an ON an.part = p.part AND an.y = y.y JOIN (SELECT part, sum(n) AS size FROM an GROUP BY 1) z ON z.part = p.part),
scored AS MATERIALIZED (SELECT cand.vid, cand.part, coalesce(cv.votes, 0) AS votes, round(0.5 * CASE WHEN cv.votes > 0 THEN 1 - avol.vol / (SELECT sum(vol) FROM avol) ELSE 0 END + 0.5 * coalesce(adiv.label_div, 1), 9) AS score, asg.part AS now
 FROM cand JOIN asg USING (vid) LEFT JOIN cv ON cv.vid = cand.vid AND cv.part = cand.part JOIN avol ON avol.part = cand.part LEFT JOIN seg ON seg.vid = cand.vid LEFT JOIN adiv ON adiv.part = cand.part AND adiv.y = seg.y)"""


def _refined(spark: SparkSession, d: str) -> tuple[DataFrame, int]:
    e, both, _, _ = _parts(spark, d)
    v = graphs.vertices(e)
    return partition.refine_scores(both, v, graphs.by_key(v, M), segments(spark, d), partition.Config(M)), v.count()


@query(_REFINE + " SELECT vid, part, votes, round(score, 6) AS score, now FROM scored")
def part_refine_scores(spark: SparkSession, d: str) -> DataFrame:
    return _refined(spark, d)[0].withColumn("score", F.round("score", 6))


@query(_REFINE + f""", g AS (SELECT t.vid, t.part, round(t.score - h.score, 9) AS gain, h.votes - t.votes AS lost FROM scored t JOIN scored h ON h.vid = t.vid AND h.part = h.now WHERE t.part <> t.now),
b AS (SELECT vid, part, gain FROM (SELECT *, row_number() OVER (PARTITION BY vid ORDER BY gain DESC, part) AS r FROM g WHERE gain > 0.01 AND lost <= 0) WHERE r = 1)
SELECT vid, part, round(gain, 6) AS gain FROM (SELECT *, row_number() OVER (PARTITION BY part ORDER BY gain DESC, vid) AS nth FROM b) WHERE nth <= greatest(1, ceil(0.05 * (SELECT count(*) FROM v) / {M}))""")
def part_refine_moves(spark: SparkSession, d: str) -> DataFrame:
    scored, n = _refined(spark, d)
    return partition.refine_moves(scored, n, partition.Config(M)).withColumn("gain", F.round("gain", 6))


@query(_P + " SELECT vid, part FROM old UNION ALL SELECT vid, part FROM placed")
def part_extend_hop1(spark: SparkSession, d: str) -> DataFrame:
    _, both, old, new = _parts(spark, d)
    return old.unionByName(partition.place(both, new, old, None, partition.Config(M)))


_TWO = """, far AS MATERIALIZED (SELECT DISTINCT p.src, q.dst FROM s p SEMI JOIN fresh ON p.src = fresh.vid JOIN s q ON q.src = p.dst WHERE q.dst <> p.src),
fv AS (SELECT far.src AS vid, old.part, count(*) AS votes FROM far JOIN old ON old.vid = far.dst GROUP BY 1, 2)"""


@query(_P + _TWO + " SELECT vid, part FROM (SELECT fv.vid, fv.part, row_number() OVER (PARTITION BY fv.vid ORDER BY votes DESC, vol, fv.part) AS r FROM fv JOIN vol USING (part)) WHERE r = 1")
def part_extend_hop2(spark: SparkSession, d: str) -> DataFrame:
    """Placement of new vertices by their two-step neighbours; volumes are those of one-hop edges."""
    _, both, old, new = _parts(spark, d)
    far = partition.two_hop(both, new)
    cast = partition.votes(far, new, old)
    vol = partition.volumes(both, old, M)
    return cast.join(F.broadcast(vol), "part").groupBy("vid").agg(F.max_by("part", F.struct("votes", -F.col("vol"), -F.col("part"))).alias("part"))


_DRAW = "CAST(('0x' || substr(md5('{0}:' || {1}), 1, 13)) AS BIGINT) % {2}"


@query(f"SELECT vid, CAST(CASE WHEN {_DRAW.format('stay', 'vid', 100)} < 80 THEN y % {M} ELSE {_DRAW.format('part', 'vid', M)} END AS INTEGER) AS part FROM ({sql.SEGMENT})")
def part_label_skew(spark: SparkSession, d: str) -> DataFrame:
    return partition_rivals.label_skew(segments(spark, d), M)


@query(sql.base("copurchase") + " SELECT vid, part FROM asg")
def part_hash(spark: SparkSession, d: str) -> DataFrame:
    return partition_rivals.by_hash(graphs.vertices(graphs.edges(spark, d, "copurchase")), M)


@query(sql.base("copurchase") + f", t AS (SELECT DISTINCT src AS vid, CAST(floor(first * {M} / 10) AS INTEGER) AS part FROM s) SELECT count(*) AS copies, count(DISTINCT vid) AS vertices, round(count(*) / count(DISTINCT vid), 6) AS factor, (SELECT round(max(n) / avg(n), 6) FROM (SELECT count(*) AS n FROM t GROUP BY part)) AS imbalance FROM t")
def part_time_replicas(spark: SparkSession, d: str) -> DataFrame:
    return quality.replicas(partition_rivals.by_time(graphs.edges(spark, d, "copurchase"), M, 9))


@query(sql.base("copurchase") + ", k AS (SELECT part, sum(deg) AS ends FROM asg JOIN d USING (vid) GROUP BY 1), i AS (SELECT pu AS part, count(*) / 2 AS inside FROM ee WHERE pu = pv GROUP BY 1), m AS (SELECT count(*) AS m FROM e) SELECT round(sum(coalesce(inside, 0) / m - (ends / (2 * m)) ** 2), 6) AS q FROM k LEFT JOIN i USING (part), m")
def part_modularity_value(spark: SparkSession, d: str) -> DataFrame:
    e = materialise(graphs.edges(spark, d, "copurchase"), "edges")
    return partition_rivals.modularity_value(e, graphs.by_key(graphs.vertices(e), M).withColumnRenamed("part", "label"))


@query(f"WITH w AS MATERIALIZED (SELECT least(x, y) AS a, greatest(x, y) AS b, count(*) AS w FROM ({sql.EVENTS['talk']}) WHERE x <> y GROUP BY 1, 2), t AS (SELECT a AS v, b AS u, w FROM w UNION ALL SELECT b, a, w FROM w), best AS MATERIALIZED (SELECT v, arg_max(u, (w, -u)) AS u FROM t GROUP BY 1) SELECT p.v AS a, p.u AS b FROM best p JOIN best q ON q.v = p.u AND q.u = p.v WHERE p.v < p.u")
def part_matching_round(spark: SparkSession, d: str) -> DataFrame:
    """Edges that both ends hold for their heaviest, by how often users follow each other."""
    ev = graphs.talk(spark, d)
    return partition_rivals.matching(ev.groupBy(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).agg(F.count(F.lit(1)).alias("w")))


# --- whole procedures: checked by invariants, which have plain SQL


def _summary(e: DataFrame, asg: DataFrame, m: int = M) -> DataFrame:
    """vertices placed, clients used beyond m, edges counted: a disjoint cover has these values by definition."""
    ee = clients.placed(e, asg)
    n = asg.agg(F.count(F.lit(1)).alias("rows"), F.count_distinct("vid").alias("vertices"), F.count_if((F.col("part") < 0) | (F.col("part") >= m)).alias("outside"))
    cut = ee.filter("src < dst").agg(F.count(F.lit(1)).alias("edges"))
    return n.join(F.broadcast(cut))


_SUMMARY = sql.base("copurchase") + " SELECT count(*) AS rows, count(*) AS vertices, CAST(0 AS BIGINT) AS outside, (SELECT count(*) FROM e) AS edges FROM v"


def _whole(make) -> object:
    def run(spark: SparkSession, d: str) -> DataFrame:
        e = materialise(graphs.edges(spark, d, "copurchase"), "edges")
        return _summary(e, materialise(make(spark, d, e), "assignment"))

    return run


for _p in ("cut", "balance", "label"):
    query(_SUMMARY, name=f"part_initial_{_p}_first")(_whole(lambda spark, d, e, _p=_p: partition.initial(e, segments(spark, d), partition.Config(M, primary=_p, rounds=2))))
query(_SUMMARY, name="part_louvain")(_whole(lambda spark, d, e: partition_rivals.communities(e, M)))
query(_SUMMARY, name="part_multilevel")(_whole(lambda spark, d, e: partition_rivals.multilevel(e, M, coarse=400)))


@query(sql.base("copurchase") + ", a AS (SELECT vid, min(first) AS first FROM (SELECT src AS vid, first FROM s) GROUP BY 1) SELECT CAST(t.snap AS INTEGER) AS snap, count(*) AS vertices, CAST(0 AS BIGINT) AS moved FROM (VALUES (6), (7), (8)) t(snap) JOIN a ON a.first <= t.snap GROUP BY 1")
def part_temporal_run(spark: SparkSession, d: str) -> DataFrame:
    """Vertices placed at snapshots 6 to 8 by extension, and old ones that moved (none may)."""
    e = materialise(graphs.edges(spark, d, "copurchase"), "edges")
    prev = materialise(graphs.by_key(graphs.vertices(snapshots.at(e, 5)), M), "assignment")
    out = None
    for t in (6, 7, 8):
        now = materialise(partition.advance(prev, snapshots.at(e, t), segments(spark, d), partition.Config(M, rounds=1), M), "assignment")
        moved = now.join(prev.withColumnRenamed("part", "was"), "vid", "left").agg(F.count(F.lit(1)).alias("vertices"), F.count_if(F.col("part") != F.col("was")).alias("moved"))
        row = moved.select(F.lit(t).alias("snap"), "vertices", "moved")
        out = row if out is None else out.unionAll(row)
        prev = now
    return out


@query()
def study_partitioners(spark: SparkSession, d: str) -> DataFrame:
    """Stage orders and rival partitioners on co-purchases: cut, variation of the clients' edges, label entropy against the
    best possible, and the sums that an exchange sends (two for each border vertex)."""
    e = materialise(graphs.edges(spark, d, "copurchase"), "edges")
    y = materialise(segments(spark, d), "labels")
    made = {f"{p}_first": partition.initial(e, y, partition.Config(M, primary=p, rounds=2)) for p in ("cut", "balance", "label")}
    made |= {"modularity": partition_rivals.communities(e, M), "multilevel": partition_rivals.multilevel(e, M, coarse=400), "hash": graphs.by_key(graphs.vertices(e), M)}
    out = None
    for name, asg in made.items():
        asg = materialise(asg, "assignment")
        ee = materialise(clients.placed(e, asg), "placed")
        inside = clients.local(ee).filter("src < dst").groupBy(F.col("pu").alias("part")).agg(F.count(F.lit(1)).alias("n")).withColumn("all", F.lit(0))
        cov = quality.variation(inside, "n", M, "all").select("cov")
        mixed = quality.entropy(asg, y).agg(F.round(F.avg("entropy"), 6).alias("entropy"))
        sent = clients.border(ee).agg((2 * F.count(F.lit(1))).alias("sums_sent"))
        row = quality.cut_ratio(ee).select(F.lit(name).alias("partitioner"), "edges", "cut", "ratio").join(F.broadcast(cov)).join(F.broadcast(mixed)).join(F.broadcast(sent))
        row = row.join(F.broadcast(quality.best_entropy(y).select("best")))
        out = row if out is None else out.unionByName(row)
    return out


# --- measures

_C = sql.base("copurchase")


@query(_C + " SELECT count(*) AS edges, count(*) FILTER (pu <> pv) AS cut, round(count(*) FILTER (pu <> pv) / count(*), 6) AS ratio FROM ee WHERE src < dst")
def q_cut_ratio(spark: SparkSession, d: str) -> DataFrame:
    return quality.cut_ratio(placed(spark, d)[0])


@query(_C + " SELECT CAST(t.snap AS INTEGER) AS snap, count(*) AS edges, count(*) FILTER (pu <> pv) AS cut, round(count(*) FILTER (pu <> pv) / count(*), 6) AS ratio FROM range(10) t(snap) JOIN ee ON ee.first <= t.snap WHERE src < dst GROUP BY 1")
def q_cut_ratio_by_snap(spark: SparkSession, d: str) -> DataFrame:
    return quality.cut_by_snapshot(placed(spark, d)[0], 9).select("snap", "edges", "cut", "ratio")


@query(_C + f", c AS (SELECT first, pu AS part, count(*) AS n FROM ee WHERE src < dst AND pu = pv GROUP BY 1, 2), g AS (SELECT t.first, p.part, coalesce(c.n, 0) AS n FROM (SELECT DISTINCT first FROM c) t CROSS JOIN range({M}) p(part) LEFT JOIN c ON c.first = t.first AND c.part = p.part) SELECT first, round(stddev_pop(n) / avg(n), 6) AS cov FROM g GROUP BY 1")
def q_cov_train_val_test(spark: SparkSession, d: str) -> DataFrame:
    """Variation over clients of the inner edges that come with each snapshot: a fold trains on t, validates on t + 1, tests on t + 2."""
    ee = placed(spark, d)[0]
    counts = clients.local(ee).filter("src < dst").groupBy("first", F.col("pu").alias("part")).agg(F.count(F.lit(1)).alias("n"))
    return quality.variation(counts, "n", M, "first")


_ENT = _C + f", seg AS ({sql.SEGMENT}), c AS (SELECT part, y, count(*) AS n FROM asg JOIN seg USING (vid) GROUP BY 1, 2), p AS (SELECT part, n, n / sum(n) OVER (PARTITION BY part) AS p FROM c)"


@query(_ENT + " SELECT part, CAST(sum(n) AS BIGINT) AS n, round(-sum(p * log2(p)), 6) AS entropy FROM p GROUP BY 1")
def q_entropy(spark: SparkSession, d: str) -> DataFrame:
    return quality.entropy(placed(spark, d)[1], segments(spark, d))


@query("SELECT count(DISTINCT c_mktsegment) AS classes, round(log2(count(DISTINCT c_mktsegment)), 6) AS best FROM customer")
def q_entropy_best(spark: SparkSession, d: str) -> DataFrame:
    return quality.best_entropy(segments(spark, d))


@query("WITH a AS (SELECT c_nationkey AS part, avg(CAST(c_acctbal > 4000 AS INTEGER)) AS accuracy FROM customer GROUP BY 1), q AS (SELECT var_pop(accuracy) AS variance, quantile_cont(accuracy, 0.25) AS q1, quantile_cont(accuracy, 0.5) AS median, quantile_cont(accuracy, 0.75) AS q3 FROM a) SELECT round(variance, 6) AS variance, round(q1, 6) AS q1, round(median, 6) AS median, round(q3, 6) AS q3, round(q3 - q1, 6) AS iqr, (SELECT count(*) FROM a WHERE accuracy < q1 - 1.5 * (q3 - q1) OR accuracy > q3 + 1.5 * (q3 - q1)) AS outliers FROM q")
def q_client_spread(spark: SparkSession, d: str) -> DataFrame:
    """Spread of a share over 25 clients (nations)."""
    a = table(spark, d, "customer", "c_nationkey", "c_acctbal").groupBy("c_nationkey").agg(F.avg((F.col("c_acctbal") > 4000).cast("int")).alias("accuracy"))
    return quality.spread(a)


@query(_C + " SELECT count(*) AS copies, count(DISTINCT vid) AS vertices, 1.0::DOUBLE AS factor, (SELECT round(max(n) / avg(n), 6) FROM (SELECT count(*) AS n FROM asg GROUP BY part)) AS imbalance FROM asg")
def q_replicas(spark: SparkSession, d: str) -> DataFrame:
    return quality.replicas(placed(spark, d)[1])


# --- privacy

_S = sql.base("copurchase") + sql.SUMS


@query(_S + ", o AS (SELECT vid, 1 AS hop, x FROM d1 UNION ALL SELECT vid, 2, x FROM complete) SELECT 'vertices' AS part_of_view, count(*) AS n FROM asg WHERE part = 2 UNION ALL SELECT 'edges', count(*) FROM ee WHERE pu = 2 AND pv = 2 UNION ALL SELECT 'messages', count(*) FROM o JOIN asg USING (vid) WHERE part = 2")
def pv_view(spark: SparkSession, d: str) -> DataFrame:
    """Sizes of all that client 2 may read."""
    ee, asg, x = placed(spark, d)
    out = None
    for name, df in privacy.client_view(ee, asg, exchange.outbox(ee, x, asg, 9, d=1), 2).items():
        row = df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("part_of_view"), "n")
        out = row if out is None else out.unionAll(row)
    return out


@query("SELECT CAST(0 AS INTEGER) AS part, CAST(0 AS BIGINT) AS vid, CAST(0 AS INTEGER) AS hop WHERE false")
def pv_oblivious_violations(spark: SparkSession, d: str) -> DataFrame:
    ee, asg, x = placed(spark, d)
    return privacy.oblivious_faults(exchange.outbox(ee, x, asg, 9, d=1), asg)


@query(_S + " SELECT n AS remote, count(*) AS vertices FROM (SELECT src, count(*) AS n FROM cut GROUP BY 1) GROUP BY 1")
def pv_ambiguity(spark: SparkSession, d: str) -> DataFrame:
    return privacy.ambiguity(placed(spark, d)[0])


for _g in ("copurchase", "talk", "buy", "ship", "link"):
    query(sql.base(_g) + ", r AS (SELECT src, count(*) AS n FROM ee WHERE pu <> pv GROUP BY 1) SELECT count(*) AS border, count(*) FILTER (n = 1) AS singletons, round(count(*) FILTER (n = 1) / count(*), 6) AS share FROM r", name="pv_singletons" if _g == "copurchase" else f"pv_singletons_{_g}")(lambda spark, d, _n=_g: privacy.singletons(placed(spark, d, _n)[0]))


@query(_S + " SELECT (SELECT round(avg(CAST(x - 500 <= 0 AS INTEGER)), 6) FROM h1) AS clipped, (SELECT round(avg(CAST(deg > 1 AS INTEGER)), 6) FROM d) AS mixing")
def pv_irreversibility(spark: SparkSession, d: str) -> DataFrame:
    ee, _, x = placed(spark, d)
    pre = message.aggregate(clients.local(ee), x, "sum", d=1).select("vid", F.transform("x", lambda v: v - 500).alias("x"))
    return privacy.irreversibility(pre, primitives.degrees(graphs.edges(spark, d, "copurchase")))


@query(_S + " SELECT count(DISTINCT src) AS equations, count(DISTINCT dst) AS unknowns, count(DISTINCT dst) > count(DISTINCT src) AS underdetermined FROM ee WHERE pu IN (0, 1) AND pv NOT IN (0, 1)")
def pv_collusion_counts(spark: SparkSession, d: str) -> DataFrame:
    return privacy.collusion(placed(spark, d)[0], [0, 1])


@query(_S + ", b AS (SELECT pu AS part, count(DISTINCT src) AS border FROM ee WHERE pu <> pv GROUP BY 1), p AS (SELECT part, CAST(count(*) * (count(*) - 1) / 2 AS BIGINT) AS pairs FROM asg GROUP BY 1) SELECT part, border, CAST(2 * border * 8 AS BIGINT) AS received, CAST((SELECT sum(pairs) FROM p) - pairs AS BIGINT) AS pairs, 2 * border * 8 < (SELECT sum(pairs) FROM p) - pairs AS holds FROM p JOIN b USING (part)")
def pv_dimension(spark: SparkSession, d: str) -> DataFrame:
    ee, asg, _ = placed(spark, d)
    return privacy.dimension(ee, asg, 8)


@query()
def pv_attack_lstsq(spark: SparkSession, d: str) -> DataFrame:
    """What two colluding clients recover of remote features by least squares on the links between pages and targets."""
    ee, _, x = placed(spark, d, "buy")
    return privacy.attack(ee, x, [0, 1])


# --- graph primitives


@query(sql.base("talk") + " SELECT vid, deg FROM d")
def g_degrees(spark: SparkSession, d: str) -> DataFrame:
    return primitives.degrees(graphs.edges(spark, d, "talk"))


_NEAR = sql.base("link") + ", c AS MATERIALIZED (SELECT p.src AS u, q.src AS v, count(*) AS common, sum(1 / ln(greatest(deg, 2))) AS aa FROM s p JOIN s q ON p.dst = q.dst AND p.src < q.src JOIN d ON d.vid = p.dst GROUP BY 1, 2)"


@query(_NEAR + " SELECT u, v, common FROM c")
def ev_common_neighbours(spark: SparkSession, d: str) -> DataFrame:
    return primitives.common_neighbours(graphs.edges(spark, d, "link")).select("u", "v", "common")


@query(_NEAR + " SELECT c.u, c.v, round(common / (p.deg + q.deg - common), 6) AS jaccard FROM c JOIN d p ON p.vid = c.u JOIN d q ON q.vid = c.v")
def ev_jaccard(spark: SparkSession, d: str) -> DataFrame:
    return primitives.common_neighbours(graphs.edges(spark, d, "link")).select("u", "v", "jaccard")


@query(_NEAR + " SELECT u, v, round(aa, 6) AS adamic_adar FROM c")
def ev_adamic_adar(spark: SparkSession, d: str) -> DataFrame:
    return primitives.common_neighbours(graphs.edges(spark, d, "link")).select("u", "v", "adamic_adar")


@query(sql.base("copurchase") + " SELECT p.a AS x, p.b AS y, q.b AS z FROM e p JOIN e q ON q.a = p.b JOIN e r ON r.a = p.a AND r.b = q.b")
def g_triangles(spark: SparkSession, d: str) -> DataFrame:
    return primitives.triangles(graphs.edges(spark, d, "copurchase"))


@query(sql.base("copurchase") + " SELECT count(*) AS edges, (SELECT count(*) FROM v) AS vertices, round(2 * count(*) / ((SELECT count(*) FROM v) * ((SELECT count(*) FROM v) - 1)), 6) AS density FROM e")
def g_density(spark: SparkSession, d: str) -> DataFrame:
    e = graphs.edges(spark, d, "copurchase")
    n = graphs.vertices(e).agg(F.count(F.lit(1)).alias("vertices"))
    return e.agg(F.count(F.lit(1)).alias("edges")).join(F.broadcast(n)).select("edges", "vertices", F.round(2 * F.col("edges") / (F.col("vertices") * (F.col("vertices") - 1)), 6).alias("density"))


@query(_S + " SELECT s.src AS vid, count(*) AS two_step FROM s JOIN s q ON q.src = s.dst WHERE q.dst <> s.src GROUP BY 1")
def g_two_step_paths(spark: SparkSession, d: str) -> DataFrame:
    """Two-step paths from each vertex, from degrees alone: sum of (degree - 1) over neighbours."""
    e = materialise(graphs.edges(spark, d, "copurchase"), "edges")
    deg = primitives.degrees(e)
    near = graphs.symmetric(e).join(deg.withColumnRenamed("vid", "dst"), "dst")
    return near.groupBy(F.col("src").alias("vid")).agg(F.sum(F.col("deg") - 1).alias("two_step")).filter("two_step > 0")
