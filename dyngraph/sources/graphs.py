"""Evolving graphs on the given tables.

Every builder returns edge events (x, y, snap): vertex ids are key * 8 + kind, with kind 0 customer, 1 order, 2 part,
3 supplier, 4 user, 5 property key, 6 page, document or turn, 7 link target or source.
``edges`` turns events into undirected distinct edges (a, b, first) with a < b and the first snapshot of each.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .tables import table

KINDS = {"customer": 0, "order": 1, "part": 2, "supplier": 3, "user": 4, "property": 5, "page": 6, "target": 7}


def vid(key: Column | str, kind: str) -> Column:
    return (F.col(key) if isinstance(key, str) else key).cast("long") * 8 + F.lit(KINDS[kind]).cast("long")


def key_of(v: Column | str) -> Column:
    return F.shiftright(F.col(v) if isinstance(v, str) else v, 3)


def month(ts: str) -> Column:
    """Months since January 1995."""
    return ((F.year(ts) - 1995) * 12 + F.month(ts) - 1).cast("int")


def week(ts: str) -> Column:
    """Weeks since 1 January 1995."""
    return F.floor(F.datediff(F.to_date(ts), F.lit("1995-01-01").cast("date")) / 7).cast("int")


def day(ts: str) -> Column:
    """Days since 1 January 2024."""
    return F.datediff(F.to_date(ts), F.lit("2024-01-01").cast("date")).cast("int")


def decile(key: str, df: DataFrame) -> Column:
    """Ten equal ranges of ``key``; one aggregation of the smallest and largest value."""
    ends = df.agg(F.min(key).alias("lo"), F.max(key).alias("hi"))
    lo, width = ends.select("lo").scalar(), ends.select((F.col("hi") - F.col("lo") + 1).alias("w")).scalar()
    return F.floor((F.col(key) - lo) * 10 / width).cast("int")


def buy(spark: SparkSession, d: str, every: str = "month") -> DataFrame:
    """Customer and order, by order date."""
    rule = {"week": week, "month": month}[every]
    return table(spark, d, "orders", "o_custkey", "o_orderkey", "o_orderdate").select(
        vid("o_custkey", "customer").alias("x"), vid("o_orderkey", "order").alias("y"), rule("o_orderdate").alias("snap")
    )


def _bought(spark: SparkSession, d: str) -> DataFrame:
    orders = table(spark, d, "orders", "o_orderkey", "o_custkey", "o_orderdate").select("o_orderkey", "o_custkey", month("o_orderdate").alias("m"))
    return table(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_suppkey").join(orders, F.col("l_orderkey") == F.col("o_orderkey"))


def copurchase(spark: SparkSession, d: str) -> DataFrame:
    """Customers who ordered one part in one month; eight months a snapshot."""
    # dealt once for the distinct rows and both sides of the join
    bought = _bought(spark, d).select("l_partkey", "m", "o_custkey").repartition("l_partkey", "m").distinct()
    other = bought.select("l_partkey", "m", F.col("o_custkey").alias("c2"))
    pairs = bought.join(other, ["l_partkey", "m"]).filter("o_custkey < c2")
    return pairs.select(vid("o_custkey", "customer").alias("x"), vid("c2", "customer").alias("y"), F.floor(F.col("m") / 8).cast("int").alias("snap"))


def ship(spark: SparkSession, d: str) -> DataFrame:
    """Order and part, by month of shipping."""
    return table(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_shipdate").select(
        vid("l_orderkey", "order").alias("x"), vid("l_partkey", "part").alias("y"), month("l_shipdate").alias("snap")
    )


def trade(spark: SparkSession, d: str) -> DataFrame:
    """Customer and part, by month of order."""
    return _bought(spark, d).select(vid("o_custkey", "customer").alias("x"), vid("l_partkey", "part").alias("y"), F.col("m").alias("snap"))


def talk(spark: SparkSession, d: str) -> DataFrame:
    """Users of consecutive events, by day.

    The order is taken within days; the last event of a day meets the first of the next through one row a day, so no
    window covers the whole table.
    """
    e = table(spark, d, "events", "event_id", "ts", "user_id").withColumn("snap", day("ts"))
    before = Window.partitionBy("snap").orderBy("ts", "event_id")
    within = e.select("snap", "user_id", F.lag("user_id").over(before).alias("prev")).filter("prev is not null")
    daily = e.groupBy("snap").agg(
        F.min_by("user_id", F.struct("ts", "event_id")).alias("user_id"), F.max_by("user_id", F.struct("ts", "event_id")).alias("last")
    )
    across = daily.select("snap", "user_id", F.lag("last").over(Window.orderBy("snap")).alias("prev")).filter("prev is not null")
    return within.union(across).filter("user_id <> prev").select(vid("prev", "user").alias("x"), vid("user_id", "user").alias("y"), "snap")


def userkey(spark: SparkSession, d: str) -> DataFrame:
    """User and the key in the event's properties; three days a snapshot."""
    e = table(spark, d, "events", "ts", "user_id", "props")
    return e.select(
        vid("user_id", "user").alias("x"), vid(F.get_json_object("props", "$.k"), "property").alias("y"), F.floor(day("ts") / 3).cast("int").alias("snap")
    ).filter("y is not null")


def hashed(text: Column) -> Column:
    """52 bits of the MD5 digest as an id that DuckDB can compute too."""
    return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("long")


def link(spark: SparkSession, d: str) -> DataFrame:
    """Page and the targets of its links, by tenth of page ids."""
    p = table(spark, d, "pages", "page_id", "html")
    found = p.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href"))
    return found.select(vid("page_id", "page").alias("x"), vid(hashed(F.col("href")), "target").alias("y"), decile("page_id", p).alias("snap"))


def reply(spark: SparkSession, d: str) -> DataFrame:
    """Each turn and the next of its conversation, by tenth of conversation ids."""
    c = table(spark, d, "conversations", "conv_id", "turn")
    n = c.select("conv_id", (F.col("turn") - 1).alias("turn"))
    t = lambda k: vid(F.col("conv_id") * 4096 + F.col("turn") + k, "page")
    return c.join(n, ["conv_id", "turn"]).select(t(0).alias("x"), t(1).alias("y"), decile("conv_id", c).alias("snap"))


def docs(spark: SparkSession, d: str) -> DataFrame:
    """Document and source, by tenth of document ids."""
    t = table(spark, d, "documents", "doc_id", "source")
    return t.filter("source is not null").select(
        vid("doc_id", "page").alias("x"), vid(F.substring("source", 4, 9), "target").alias("y"), decile("doc_id", t).alias("snap")
    )


def _closest(q: np.ndarray, r: np.ndarray, qid: np.ndarray, rid: np.ndarray, k: int, chunk: int = 512) -> list[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(row, other, cosine) of the k rows of r nearest to each row of q, itself left out, ties by id.

    Products of single precision choose what comes into question; cosines are then taken in double precision in an order
    that hangs on the pair alone, so equal vectors tie.
    """
    nq, nr = (np.sqrt((x * x).sum(axis=1)) for x in (q, r))
    a, b = ((x / np.maximum(n, 1e-300)[:, None]).astype(np.float32) for x, n in ((q, nq), (r, nr)))
    bt, out = np.ascontiguousarray(b.T), []
    by_id = np.argsort(rid)
    for at in range(0, len(q), chunk):
        rows = slice(at, at + chunk)
        score = a[rows] @ bt
        where = np.minimum(np.searchsorted(rid, qid[rows], sorter=by_id), len(rid) - 1)
        own = by_id[where]
        here = np.flatnonzero(rid[own] == qid[rows])
        score[here, own[here]] = -2.0
        last = np.partition(score, -k, axis=1)[:, -k] if len(r) >= k else np.full(len(score), -1.5)
        i, j = np.nonzero(score >= np.maximum(last - 1e-4, -1.5)[:, None])
        i = i + at
        exact = np.concatenate([(q[i[z : z + 65536]] * r[j[z : z + 65536]]).sum(axis=1) for z in range(0, len(i), 65536)] or [np.zeros(0)])
        exact = exact / np.maximum(nq[i] * nr[j], 1e-300)
        order = np.lexsort((rid[j], -exact, i))
        i, j, exact = i[order], j[order], exact[order]
        place = np.arange(len(i)) - np.searchsorted(i, i)
        top = place < k
        out.append((qid[i[top]], rid[j[top]], exact[top]))
    return out


def _nearest(signed: DataFrame, k: int, block: int) -> DataFrame:
    """(vec_id, other_id, score): the k nearest by cosine among the vectors of equal ``sig``, block against block.

    A signature is cut into blocks of about ``block`` vectors; two blocks meet in one task, which returns k rows a vector.
    """
    spark = signed.sparkSession
    cuts = signed.groupBy("sig").agg(F.ceil(F.count(F.lit(1)) / block).cast("int").alias("blocks"))
    cuts = spark.createDataFrame(cuts.collect(), cuts.schema)  # one row a signature
    tasks = cuts.agg(F.sum(F.col("blocks") * (F.col("blocks") + 1) / 2).alias("n")).first()["n"] or 1
    b, o = F.pmod(F.xxhash64("vec_id"), F.col("blocks")).cast("int"), F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    dealt = signed.join(F.broadcast(cuts), "sig").select("sig", "vec_id", "embedding", b.alias("b"), o.alias("o"))
    dealt = dealt.select("sig", "vec_id", "embedding", "b", F.least("b", "o").alias("i"), F.greatest("b", "o").alias("j"))

    def work(t: pa.Table) -> pa.Table:
        b, ids = t.column("b").to_numpy(), t.column("vec_id").to_numpy()
        x = np.asarray(t.column("embedding").combine_chunks().flatten(), dtype=np.float64).reshape(len(ids), -1)
        i, j = (t.column(c)[0].as_py() for c in ("i", "j"))
        one, two = np.flatnonzero(b == i), np.flatnonzero(b == j)
        found = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))]
        for q, r in ((one, two), (two, one))[: 1 + (i < j)]:
            if len(q) and len(r):
                found += _closest(x[q], x[r], ids[q], ids[r], k)
        return pa.table(dict(zip(("vec_id", "other_id", "score"), map(np.concatenate, zip(*found, strict=True)), strict=True)))

    parts = min(int(tasks), max(64, 4 * spark.sparkContext.defaultParallelism))
    near = dealt.repartition(parts, "sig", "i", "j").groupBy("sig", "i", "j").applyInArrow(work, "vec_id long, other_id long, score double")
    best = Window.partitionBy("vec_id").orderBy(F.desc("score"), "other_id")
    return near.distinct().withColumn("n", F.row_number().over(best)).filter(F.col("n") <= k).drop("n")


def vec(spark: SparkSession, d: str, k: int = 3, block: int = 4096) -> DataFrame:
    """Each vector and its k nearest by cosine (ties by id), by tenth of ids: exact, block against block.

    Memory is bounded by the block; the work is quadratic by nature. ``vec_hashed`` is the one for large tables.
    """
    e = table(spark, d, "embeddings", "vec_id", "embedding").filter("embedding is not null")
    found = _nearest(e.withColumn("sig", F.lit(0)), k, block)
    return found.select(vid("vec_id", "page").alias("x"), vid("other_id", "page").alias("y"), decile("vec_id", e).alias("snap"))


def vec_hashed(spark: SparkSession, d: str, k: int = 3, bits: int = 6, tables: int = 12, seed: int = 5, block: int = 8192) -> DataFrame:
    """As ``vec`` among vectors that share a signature of random hyperplanes in one of ``tables``; no pair is listed."""
    e = table(spark, d, "embeddings", "vec_id", "embedding").filter("embedding is not null")
    width = e.select(F.max(F.size("embedding")).alias("w")).first()["w"] or 1
    planes = np.random.default_rng(seed).normal(size=(tables, bits, width)).reshape(-1, width).T

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = np.asarray(b.column("embedding").flatten(), dtype=np.float64).reshape(-1, width)
            sides = (x @ planes >= 0).reshape(len(x), tables, bits) @ (1 << np.arange(bits, dtype=np.int64))
            sigs = (sides + (np.arange(tables, dtype=np.int64) << bits)).ravel()
            ends = pa.array(np.arange(0, len(sigs) + 1, tables, dtype=np.int32))
            yield pa.RecordBatch.from_arrays([b.column("vec_id"), b.column("embedding"), pa.ListArray.from_arrays(ends, pa.array(sigs))], names=["vec_id", "embedding", "sigs"])

    kind = dict(e.dtypes)["embedding"]
    signed = e.mapInArrow(sign, f"vec_id long, embedding {kind}, sigs array<long>").select("vec_id", "embedding", F.explode("sigs").alias("sig"))
    found = _nearest(signed, k, block)
    return found.select(vid("vec_id", "page").alias("x"), vid("other_id", "page").alias("y"), decile("vec_id", e).alias("snap"))


BUILDERS = {f.__name__: f for f in (buy, copurchase, ship, trade, talk, userkey, link, reply, docs, vec)}


def undirected(events: DataFrame) -> DataFrame:
    """Distinct edges a < b with the first snapshot; self-loops go."""
    return events.filter("x <> y").groupBy(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).agg(F.min("snap").alias("first"))


def edges(spark: SparkSession, d: str, name: str) -> DataFrame:
    return undirected(BUILDERS[name](spark, d))


def symmetric(e: DataFrame) -> DataFrame:
    """Both directions (src, dst, first) of undirected edges."""
    return e.select(F.col("a").alias("src"), F.col("b").alias("dst"), "first").unionAll(e.select("b", "a", "first"))


def vertices(e: DataFrame) -> DataFrame:
    """Distinct end points."""
    return e.select(F.col("a").alias("vid")).unionAll(e.select("b")).distinct()


def by_key(v: DataFrame, m: int = 4) -> DataFrame:
    """The fixed assignment of tests and oracles: key modulo m."""
    return v.select("vid", F.pmod(key_of("vid"), F.lit(m)).cast("int").alias("part"))


def small_feature(v: DataFrame) -> DataFrame:
    """The integer feature of tests and oracles."""
    return v.select("vid", (F.col("vid") % 97 + 1).alias("x"))
