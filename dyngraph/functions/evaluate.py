"""Ranking and classification measures, sampling, forgetting, the live-update protocol."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.tables import materialise
from .vectors import dot


def md5_int(*parts: Column | str) -> Column:
    """52 bits of an MD5 digest of the parts, as DuckDB can compute them."""
    text = F.concat_ws(":", *[(F.col(p) if isinstance(p, str) else p).cast("string") for p in parts])
    return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("long")


def dot_scores(h: DataFrame, pairs: DataFrame) -> DataFrame:
    """pairs (u, v, ...) with the dot product of their vectors."""
    one = pairs.join(h.select(F.col("vid").alias("u"), F.col("x").alias("hu")), "u")
    return one.join(h.select(F.col("vid").alias("v"), F.col("x").alias("hv")), "v").withColumn("score", dot("hu", "hv")).drop("hu", "hv")


def mrr(scores: DataFrame, ties: str = "candidate") -> DataFrame:
    """One row: queries with a positive, and the mean of one over the rank of the first.

    scores: (query, cand, score, y). Ties go by candidate id, or a positive takes the best, worst or middle place
    (``optimistic``, ``pessimistic``, ``average``).
    """
    if ties == "candidate":
        order = Window.partitionBy("query").orderBy(F.desc("score"), "cand")
        ranked = scores.withColumn("rank", F.row_number().over(order))
    else:
        by = Window.partitionBy("query").orderBy(F.desc("score"))
        low = F.rank().over(by)
        tied = F.count(F.lit(1)).over(Window.partitionBy("query", "score"))
        ranked = scores.withColumn("rank", {"optimistic": low, "pessimistic": low + tied - 1, "average": low + (tied - 1) / 2.0}[ties])
    first = ranked.filter("y = 1").groupBy("query").agg((1.0 / F.min("rank")).alias("rr"))
    return first.agg(F.count(F.lit(1)).alias("queries"), F.round(F.avg("rr"), 6).alias("mrr"))


def map_by_query(scores: DataFrame) -> DataFrame:
    """One row: mean over queries of average precision."""
    order = Window.partitionBy("query").orderBy(F.desc("score"), "cand")
    ranked = scores.select("query", "y", F.row_number().over(order).alias("rank"), F.sum("y").over(order.rowsBetween(Window.unboundedPreceding, 0)).alias("hits"))
    ap = ranked.filter("y = 1").groupBy("query").agg(F.avg(F.col("hits") / F.col("rank")).alias("ap"))
    return ap.agg(F.count(F.lit(1)).alias("queries"), F.round(F.avg("ap"), 6).alias("map"))


def global_precision(scores: DataFrame, bins: int = 256) -> DataFrame:
    """One row: average precision of all rows as one ranking, ordered by score then (query, cand).

    No window spans the table: score ranges from approximate quantiles are numbered, counted, and each range adds the
    counts before it to its own running sums.
    """
    cuts = scores.agg(F.percentile_approx("score", F.lit([i / bins for i in range(1, bins)]), 10_000).alias("c")).select(F.array_sort(F.array_distinct("c")).alias("c")).scalar()
    binned = scores.withColumn("cuts", cuts).withColumn("bin", F.size(F.filter("cuts", lambda c: c > F.col("score")))).drop("cuts")
    counts = binned.groupBy("bin").agg(F.count(F.lit(1)).alias("n"), F.sum("y").alias("h"))
    before = Window.orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)  # one row a bin
    base = counts.select("bin", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("n0"), F.coalesce(F.sum("h").over(before), F.lit(0)).alias("h0"))
    order = Window.partitionBy("bin").orderBy(F.desc("score"), "query", "cand")
    ranked = binned.join(F.broadcast(base), "bin").select("y", (F.col("n0") + F.row_number().over(order)).alias("rank"), (F.col("h0") + F.sum("y").over(order.rowsBetween(Window.unboundedPreceding, 0))).alias("hits"))
    return ranked.filter("y = 1").agg(F.count(F.lit(1)).alias("positives"), F.round(F.avg(F.col("hits") / F.col("rank")), 6).alias("map"))


def accuracy(scores: DataFrame) -> DataFrame:
    """Share of links decided rightly at a logistic score of one half, that is at dot product 0."""
    return scores.agg(F.count(F.lit(1)).alias("n"), F.round(F.avg(((F.col("score") >= 0).cast("int") == F.col("y")).cast("int")), 6).alias("accuracy"))


class Box:
    """Points ``start`` to ``end`` of an order in which those of a box, and of each box within it, stand together.

    ``size`` bounds the points of a box without further ones; ``within`` holds those with the middles and half widths of all.
    """

    FAN = 8

    def __init__(self, x: np.ndarray, order: np.ndarray, start: int, end: int, size: int) -> None:
        self.start, self.end = start, end
        low, high = (f(x[order[start:end]], axis=0) for f in (np.min, np.max))
        self.middle, self.half = (low + high) / 2, (high - low) / 2
        parts = [(start, end)]
        while len(parts) < self.FAN and any(e - s > size for s, e in parts):
            parts = [p for s, e in parts for p in (self.halved(x, order, s, e) if e - s > size else [(s, e)])]
        self.within = [Box(x, order, s, e, size) for s, e in parts] if len(parts) > 1 else []
        self.middles, self.halves = (np.array([getattr(b, k) for b in self.within]) for k in ("middle", "half"))
        self.sizes = np.array([b.end - b.start for b in self.within])

    @staticmethod
    def halved(x: np.ndarray, order: np.ndarray, start: int, end: int) -> list[tuple[int, int]]:
        """Halves by the widest dimension."""
        own, half = order[start:end], (end - start) // 2
        part = x[own]
        order[start:end] = own[np.argpartition(part[:, (part.max(axis=0) - part.min(axis=0)).argmax()], half)]
        return [(start, start + half), (start + half, end)]


def ahead(q: np.ndarray, s: np.ndarray, cand: np.ndarray, c: np.ndarray, ids: np.ndarray, size: int = 64, chunk: int = 1 << 15) -> np.ndarray:
    """For each row of ``q``, how many rows of ``c`` have a dot product over ``s``, or equal to it and an id below ``cand``.

    Boxes within boxes, along the main axes of ``c``: those whose bounds lie on one side of ``s`` count as a whole, and only
    the others are opened. Products within rounding of ``s`` are taken again in the order of ``vectors.dot``, so that ties are
    those of the scores.
    """
    n = np.zeros(len(q), np.int64)
    if not len(c):
        return n
    edge = np.abs(q).sum(axis=1) * np.abs(c).max() * 1e-13 + 1e-300
    under, over = s - edge, s + edge
    turn = np.linalg.eigh(np.cov(c.T).reshape(c.shape[1], -1))[1] if len(c) > 1 else np.eye(c.shape[1])
    order, size = np.arange(len(c)), min(size, 127)  # counts of a box fit 8 bits
    root = Box(c @ turn, order, 0, len(c), size)
    held = c[order]
    count = lambda told: np.add.reduce(told.view(np.int8), axis=0, dtype=np.int8)

    def opened(box: Box, rows: np.ndarray, part: np.ndarray, turned: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> None:
        """Adds what the points of a box give for ``rows``, whose vectors are columns here."""
        if box.within:
            mid, off = box.middles @ turned, box.halves @ np.abs(turned)
            whole = mid - off > hi
            n[rows] += box.sizes @ whole
            unsure = ~whole & (mid + off >= lo)
            for j, inner in enumerate(box.within):
                w = np.flatnonzero(unsure[j])
                if len(w):
                    opened(inner, rows[w], part[:, w], turned[:, w], lo[w], hi[w])
            return
        score = held[box.start : box.end] @ part
        over, maybe = score > hi, score >= lo
        sure = count(over)
        n[rows] += sure
        near = np.flatnonzero(count(maybe) != sure)
        if len(near):
            k, i = np.nonzero(maybe[:, near] & ~over[:, near])
            i, k, again = rows[near[i]], order[box.start + k], 0.0
            for dim in range(c.shape[1]):
                again = again + q[i, dim] * c[k, dim]
            np.add.at(n, i, (again > s[i]) | ((again == s[i]) & (ids[k] < cand[i])))

    for at in range(0, len(q), chunk):
        rows = np.arange(at, min(at + chunk, len(q)))
        opened(root, rows, np.ascontiguousarray(q[rows].T), np.ascontiguousarray((q[rows] @ turn).T), under[rows], over[rows])
    return n


def _counter() -> Callable[[pa.Table, pa.Table], pa.Table]:
    """Counts a block of rows against a block of candidates; a query is no candidate of its own."""

    def work(left: pa.Table, right: pa.Table) -> pa.Table:
        from ..operators.message import matrix

        kind = pa.schema([("query", pa.int64()), ("cand", pa.int64()), ("above", pa.int64()), ("of", pa.int64())])
        if not left.num_rows or not right.num_rows:
            return kind.empty_table()
        query, cand, s = (left.column(k).to_numpy() for k in ("query", "cand", "score"))
        q, c, ids = matrix(left.column("x").combine_chunks()), matrix(right.column("x").combine_chunks()), right.column("vid").to_numpy()
        n, own, self_ = ahead(q, s, cand, c, ids), np.isin(query, ids), 0.0
        for dim in range(q.shape[1]):
            self_ = self_ + q[:, dim] * q[:, dim]
        n -= own & ((self_ > s) | ((self_ == s) & (query < cand)))
        return pa.table([query, cand, n, len(ids) - own.astype(np.int64)], schema=kind)

    return work


def link_measures(h: DataFrame, pos: DataFrame, cands: DataFrame, block: int = 1 << 18, rows: int = 1 << 18) -> DataFrame:
    """One row (queries, mrr, map, accuracy): every query of ``pos`` (query, cand) against all ``cands`` (vid) by dot products.

    Equal to ``mrr``, ``map_by_query`` and ``accuracy`` over all pairs, of which none is listed: blocks of positives meet
    blocks of candidates and count who is ahead. Positives that are no candidates rank among their query's pairs too.
    """
    spark, x = h.sparkSession, F.col("x").cast("array<double>")
    c = materialise(h.join(cands, "vid", "left_semi").select("vid", x.alias("x")), "candidates")
    known = pos.select(F.col("query").alias("u"), F.col("cand").alias("v"))
    scored = dot_scores(h, known).select(F.col("u").alias("query"), F.col("v").alias("cand"), "score")
    inside = c.select(F.col("vid").alias("cand"), F.lit(True).alias("inside"))
    scored = materialise(scored.join(inside, "cand", "left").select("query", "cand", "score", F.coalesce("inside", F.lit(False)).alias("inside")), "positives")
    # a last row a query counts the scores that accuracy takes for links: 0 and more
    queries = scored.select("query").unionAll(known.select("u").join(h.select(F.col("vid").alias("u")), "u", "left_semi")).distinct()
    asked = scored.select("query", "cand", "score").unionAll(queries.select("query", F.lit(2**63 - 1), F.lit(0.0)))
    blocks, n = -(-c.count() // block) or 1, scored.count()
    groups = max(-(-n // rows), min(-(-2 * spark.sparkContext.defaultParallelism // blocks), n // 1024), 1)  # each gets all candidates
    each = lambda k: F.explode(F.sequence(F.lit(0), F.lit(k - 1)))
    left = asked.join(h.select(F.col("vid").alias("query"), x.alias("x")), "query").withColumn("group", F.pmod(F.xxhash64("query"), F.lit(groups)).cast("int")).select("*", each(blocks).alias("block"))
    right = c.withColumn("block", F.pmod(F.xxhash64("vid"), F.lit(blocks)).cast("int")).select("*", each(groups).alias("group"))
    left, right = (df.repartition(groups * blocks, "group", "block").groupBy("group", "block") for df in (left, right))
    parts = left.cogroup(right).applyInArrow(_counter(), "query long, cand long, above long, of long")
    counts = materialise(parts.groupBy("query", "cand").agg(F.sum("above").alias("above"), F.sum("of").alias("of")), "counts")
    order = Window.partitionBy("query").orderBy(F.desc("score"), "cand")
    outside = F.sum((~F.col("inside")).cast("long")).over(order.rowsBetween(Window.unboundedPreceding, 0)) - (~F.col("inside")).cast("long")
    ranked = scored.join(counts, ["query", "cand"], "left").select("query", (1 + F.coalesce("above", F.lit(0)) + outside).alias("rank"), F.row_number().over(order).alias("hits"))
    by_query = ranked.groupBy("query").agg((1.0 / F.min("rank")).alias("rr"), F.avg(F.col("hits") / F.col("rank")).alias("ap"))
    means = by_query.agg(F.count(F.lit(1)).alias("queries"), F.round(F.avg("rr"), 6).alias("mrr"), F.round(F.avg("ap"), 6).alias("map"))
    yes, no = F.col("score") >= 0, (F.col("score") < 0) & F.col("inside")
    told = scored.agg(*[F.coalesce(F.sum(v.cast("long")), F.lit(0)).alias(k) for k, v in (("yes", yes), ("no", no), ("added", ~F.col("inside")))])
    grid = counts.filter(F.col("cand") == 2**63 - 1).agg(F.coalesce(F.sum("above"), F.lit(0)).alias("above"), F.coalesce(F.sum("of"), F.lit(0)).alias("of"))
    right = F.col("yes") + F.col("of") - F.col("above") - F.col("no")
    return means.join(F.broadcast(told.join(F.broadcast(grid)))).select("queries", "mrr", "map", F.round(F.try_divide(right, F.col("of") + F.col("added")), 6).alias("accuracy"))


def f1(pred: DataFrame, average: str = "macro") -> DataFrame:
    """One row f1 from (y, yhat); macro over classes present in truth or prediction, micro, or weighted by truth."""
    conf = pred.groupBy("y", "yhat").agg(F.count(F.lit(1)).alias("n"))
    long = conf.select(F.col("y").alias("c"), F.when(F.col("y") == F.col("yhat"), F.col("n")).otherwise(0).alias("tp"), F.lit(0).cast("long").alias("p"), F.col("n").alias("t"))
    long = long.unionAll(conf.select(F.col("yhat").alias("c"), F.lit(0).cast("long"), F.col("n"), F.lit(0).cast("long")))
    per = long.groupBy("c").agg(F.sum("tp").alias("tp"), F.sum("p").alias("p"), F.sum("t").alias("t"))
    per = per.withColumn("f", F.when(F.col("p") + F.col("t") > 0, 2.0 * F.col("tp") / (F.col("p") + F.col("t"))).otherwise(0.0))
    how = {"macro": F.avg("f"), "micro": F.sum("tp") / F.sum("t"), "weighted": F.sum(F.col("f") * F.col("t")) / F.sum("t")}[average]
    return per.agg(F.round(how, 6).alias("f1"))


def forgetting(matrix: DataFrame, peak: bool = False) -> DataFrame:
    """One row: mean over earlier tasks of score when learnt (or best before the end) minus score at the end.

    matrix: (task, after_task, score)
    """
    end = matrix.agg(F.max("after_task").alias("t")).select("t").scalar()
    last = matrix.filter(F.col("after_task") == end).select("task", F.col("score").alias("final"))
    if peak:
        before = matrix.filter(F.col("after_task") < end).groupBy("task").agg(F.max("score").alias("was"))
    else:
        before = matrix.filter(F.col("after_task") == F.col("task")).select("task", F.col("score").alias("was"))
    return before.join(last, "task").filter(F.col("task") < end).agg(F.count(F.lit(1)).alias("tasks"), F.round(F.avg(F.col("was") - F.col("final")), 6).alias("forgetting"))


def improvement(results: DataFrame, ours: str) -> DataFrame:
    """(measure, best rival, ours, gain): relative to the best of the other methods; rows (measure, method, value)."""
    mine = results.filter(F.col("method") == ours).select("measure", F.col("value").alias("ours"))
    best = results.filter(F.col("method") != ours).groupBy("measure").agg(F.max("value").alias("best"))
    return best.join(mine, "measure").select("measure", "best", "ours", F.round((F.col("ours") - F.col("best")) / F.col("best"), 6).alias("gain"))


def summarise(results: DataFrame, by: str, column: str) -> DataFrame:
    return results.groupBy(by).agg(F.count(F.lit(1)).alias("n"), F.round(F.avg(column), 6).alias("mean"), F.round(F.stddev_samp(column), 6).alias("std"))


def ranked_vertices(assigned: DataFrame) -> DataFrame:
    """(vid, part, rank, size): vertices numbered from 0 within each client, in order of id.

    Numbers come from sorted blocks of ids and counts before them, so a large client is not one window.
    """
    block = F.floor(F.col("vid") / 65_536)
    b = assigned.select("vid", "part", block.alias("block"))
    counts = b.groupBy("part", "block").agg(F.count(F.lit(1)).alias("n"))
    base = counts.select("part", "block", F.coalesce(F.sum("n").over(Window.partitionBy("part").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("n0"), F.sum("n").over(Window.partitionBy("part")).alias("size"))
    inner = Window.partitionBy("part", "block").orderBy("vid")
    return b.join(base, ["part", "block"]).select("vid", "part", (F.col("n0") + F.row_number().over(inner) - 1).alias("rank"), "size")


def negatives(positives: DataFrame, assigned: DataFrame, both: DataFrame, seed: str, tries: int = 8) -> DataFrame:
    """(u, v, neg): for each positive (u, v) of one client a vertex of the same client that is no neighbour of u.

    Try k picks rank md5(seed, u, v, k) modulo the client's size; the first of ``tries`` that is neither u nor an
    edge is taken, none if all fail.
    """
    ranked = ranked_vertices(assigned)
    sizes = ranked.select("part", "size").distinct()
    at = positives.join(assigned.select(F.col("vid").alias("u"), "part"), "u").join(F.broadcast(sizes), "part")
    k = F.explode(F.sequence(F.lit(1), F.lit(tries))).alias("k")
    cand = at.select("u", "v", "part", "size", k).withColumn("rank", F.pmod(md5_int(F.lit(seed), "u", "v", "k"), F.col("size")))
    cand = cand.join(ranked.select("part", "rank", F.col("vid").alias("neg")), ["part", "rank"]).filter("neg <> u")
    cand = cand.join(both.select(F.col("src").alias("u"), F.col("dst").alias("neg")), ["u", "neg"], "left_anti")
    return cand.groupBy("u", "v").agg(F.min_by("neg", "k").alias("neg"))


def cut_edge_task(ee: DataFrame, assigned: DataFrame, seed: str, m: int) -> DataFrame:
    """(u, v, y): cut edges, and as many pairs of vertices of two different clients that are no edge.

    Twice as many pairs as needed are drawn by md5 of their number; distinct ones are kept in order of the digest.
    """
    pos = ee.filter("src < dst and pu <> pv").select(F.col("src").alias("u"), F.col("dst").alias("v"))
    n = pos.agg(F.count(F.lit(1)).alias("n")).first()["n"]
    ranked = ranked_vertices(assigned)
    sizes = ranked.select("part", "size").distinct()
    draw = ee.sparkSession.range(2 * n).select("id")
    draw = draw.withColumn("p", F.pmod(md5_int(F.lit(seed), F.lit("p"), "id"), F.lit(m)).cast("int"))
    draw = draw.withColumn("q", F.pmod(F.col("p") + 1 + F.pmod(md5_int(F.lit(seed), F.lit("q"), "id"), F.lit(m - 1)), F.lit(m)).cast("int"))
    for c, v, r in (("p", "u0", "ru"), ("q", "v0", "rv")):
        size = sizes.select(F.col("part").alias(c), F.col("size").alias(f"n{c}"))
        draw = draw.join(F.broadcast(size), c).withColumn(r, F.pmod(md5_int(F.lit(seed), F.lit(r), "id"), F.col(f"n{c}")))
        draw = draw.join(ranked.select(F.col("part").alias(c), F.col("rank").alias(r), F.col("vid").alias(v)), [c, r])
    pairs = draw.groupBy(F.least("u0", "v0").alias("u"), F.greatest("u0", "v0").alias("v")).agg(F.min("id").alias("id"))
    pairs = pairs.join(ee.filter("src < dst").select(F.col("src").alias("u"), F.col("dst").alias("v")), ["u", "v"], "left_anti")
    neg = pairs.orderBy("id").limit(n).select("u", "v")
    return pos.withColumn("y", F.lit(1)).unionAll(neg.withColumn("y", F.lit(0)))


def live_update_folds(last: int, spark) -> DataFrame:
    """(train, validate, test): snapshots t, t + 1, t + 2 for every t that has both."""
    return spark.range(max(0, last - 1)).select(F.col("id").cast("int").alias("train"), (F.col("id") + 1).cast("int").alias("validate"), (F.col("id") + 2).cast("int").alias("test"))


def degree_scores(history: DataFrame, queries: DataFrame) -> DataFrame:
    """(query, cand, score, y) with the candidate's degree so far as its score: the probe of degree bias."""
    deg = history.groupBy(F.col("src").alias("cand")).agg(F.count(F.lit(1)).alias("deg"))
    return queries.join(deg, "cand", "left").select("query", "cand", F.coalesce("deg", F.lit(0)).cast("double").alias("score"), "y")
