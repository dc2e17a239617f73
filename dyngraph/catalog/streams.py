"""Queries: replays of the events table as streams, and the extension surface (Python functions of every kind)."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf

from ..operators import message
from ..sources import graphs
from ..sources.tables import materialise, table
from ..streaming import edges
from .registry import query

_DONE = "(SELECT max(ts) - INTERVAL 10 MINUTE FROM events)"


@query("SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, count(*) AS edges FROM events GROUP BY 1")
def st_tumbling_edges(spark: SparkSession, d: str) -> DataFrame:
    out = edges.drained(edges.tumbling(edges.source(spark, d)), "complete")
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "edges")


@query("SELECT CAST(CAST(ts AS DATE) - k.k AS VARCHAR) AS day, count(*) AS edges FROM events, (VALUES (0), (1), (2)) k(k) GROUP BY 1")
def st_sliding_edges(spark: SparkSession, d: str) -> DataFrame:
    out = edges.drained(edges.sliding(edges.source(spark, d)), "complete")
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "edges")


@query("WITH m AS (SELECT user_id, ts, CASE WHEN ts >= coalesce(lag(ts) OVER (PARTITION BY user_id ORDER BY ts), TIMESTAMP '1970-01-01') + INTERVAL 6 HOUR THEN 1 ELSE 0 END AS f FROM events), i AS (SELECT *, sum(f) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM m) SELECT user_id, epoch_us(min(ts)) AS start, count(*) AS events FROM i GROUP BY user_id, g")
def st_sessions(spark: SparkSession, d: str) -> DataFrame:
    return edges.drained(edges.sessions(edges.source(spark, d)), "complete").select("user_id", F.unix_micros("start").alias("start"), "events")


@query("SELECT event_id FROM events")
def st_dedup(spark: SparkSession, d: str) -> DataFrame:
    """Every event is delivered twice; each comes out once."""
    s = edges.source(spark, d)
    return edges.drained(edges.deduplicated(s.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))))


@query("SELECT event_id, user_id * 8 + 4 AS u, CAST(json_extract_string(props, '$.k') AS BIGINT) * 8 + 5 AS v, CAST(user_id % 4 AS INTEGER) AS part FROM events")
def st_static_join(spark: SparkSession, d: str) -> DataFrame:
    users = table(spark, d, "events", "user_id").distinct().select(graphs.vid("user_id", "user").alias("vid"))
    return edges.drained(edges.with_clients(edges.source(spark, d), graphs.by_key(users)))


@query("SELECT p.event_id AS a, q.event_id AS b FROM events p JOIN events q ON json_extract_string(p.props, '$.k') = json_extract_string(q.props, '$.k') AND p.event_type = 'view' AND q.event_type = 'purchase' AND q.ts >= p.ts AND q.ts <= p.ts + INTERVAL 5 MINUTE")
def st_stream_join(spark: SparkSession, d: str) -> DataFrame:
    return edges.drained(edges.paired(edges.source(spark, d)))


@query("WITH v AS (SELECT user_id * 8 + 4 AS vid, CAST(CAST(json_extract_string(props, '$.k') AS BIGINT) % 4 AS INTEGER) AS part, count(*) AS n FROM events GROUP BY 1, 2) SELECT vid, arg_max(part, (n, -part)) AS part FROM v GROUP BY 1")
def st_placement(spark: SparkSession, d: str) -> DataFrame:
    return edges.drained(edges.placement(edges.source(spark, d), 4))


@query("SELECT (SELECT count(*) FROM events WHERE ts < TIMESTAMP '2024-01-20') AS in_time, (SELECT count(*) FROM events WHERE ts >= TIMESTAMP '2024-01-20') AS corrections")
def st_late_rows(spark: SparkSession, d: str) -> DataFrame:
    """Rows of a snapshot closed on 20 January, and those that go to its correction."""
    on, late = edges.with_late(edges.source(spark, d), "2024-01-20 00:00:00")
    a = edges.drained(on.select("event_id")).agg(F.count(F.lit(1)).alias("in_time"))
    return a.join(F.broadcast(edges.drained(late.select("event_id")).agg(F.count(F.lit(1)).alias("corrections"))))


# --- extension surface


@query("SELECT p_partkey, round(p_retailprice * 1.5 + p_size, 6) AS x FROM part")
def u_pandas_scalar(spark: SparkSession, d: str) -> DataFrame:
    @pandas_udf("double")
    def scaled(price: pd.Series, size: pd.Series) -> pd.Series:
        return price * 1.5 + size

    return table(spark, d, "part", "p_partkey", "p_retailprice", "p_size").select("p_partkey", F.round(scaled("p_retailprice", "p_size"), 6).alias("x"))


@query("SELECT vec_id AS vid, round(greatest(CAST(embedding[1] AS DOUBLE) - CAST(embedding[2] AS DOUBLE), 0), 5) AS x FROM embeddings")
def u_arrow_batch(spark: SparkSession, d: str) -> DataFrame:
    """A dense layer over batches of vectors."""
    w = np.zeros((64, 1))
    w[0], w[1] = 1.0, -1.0
    h = table(spark, d, "embeddings", "vec_id", "embedding").select(F.col("vec_id").alias("vid"), F.col("embedding").alias("x"))
    return message.dense(h, w, "relu").select("vid", F.round(F.get("x", F.lit(0)), 5).alias("x"))


@query("SELECT c_nationkey, count(*) AS n, round(max(c_acctbal) - min(c_acctbal), 6) AS spread FROM customer GROUP BY 1")
def u_grouped_map(spark: SparkSession, d: str) -> DataFrame:
    def spread(g: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"c_nationkey": [g["c_nationkey"].iloc[0]], "n": [len(g)], "spread": [round(float(g["c_acctbal"].max() - g["c_acctbal"].min()), 6)]})

    return table(spark, d, "customer", "c_nationkey", "c_acctbal").groupBy("c_nationkey").applyInPandas(spread, "c_nationkey int, n long, spread double")


@query("SELECT coalesce(c.k, s.k) AS k, coalesce(c.n, 0) AS customers, coalesce(s.n, 0) AS suppliers FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer GROUP BY 1) c FULL JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier GROUP BY 1) s ON c.k = s.k")
def u_cogroup(spark: SparkSession, d: str) -> DataFrame:
    def both(key: tuple, a: pa.Table, b: pa.Table) -> pa.Table:
        return pa.table({"k": pa.array([key[0].as_py()], pa.int32()), "customers": pa.array([a.num_rows], pa.int64()), "suppliers": pa.array([b.num_rows], pa.int64())})

    a = table(spark, d, "customer", "c_nationkey").select(F.col("c_nationkey").alias("k"))
    b = table(spark, d, "supplier", "s_nationkey").select(F.col("s_nationkey").alias("k"))
    return a.groupBy("k").cogroup(b.groupBy("k")).applyInArrow(both, "k int, customers long, suppliers long")


@query("SELECT event_type, round(median(value), 6) AS median FROM events GROUP BY 1")
def u_agg(spark: SparkSession, d: str) -> DataFrame:
    @pandas_udf("double")
    def median(v: pd.Series) -> float:
        return float(v.median())

    return table(spark, d, "events", "event_type", "value").groupBy("event_type").agg(F.round(median("value"), 6).alias("median"))


@query("SELECT n_nationkey AS vid, CAST(h.h AS INTEGER) AS hop, CAST((n_nationkey * 7 + h.h) % 25 AS INTEGER) AS next FROM nation, (VALUES (1), (2), (3)) h(h)")
def u_udtf(spark: SparkSession, d: str) -> DataFrame:
    """A table function that walks on from each row."""

    @udtf(returnType="hop: int, next: int")
    class Walk:
        def eval(self, vid: int) -> Iterator[tuple[int, int]]:
            for hop in (1, 2, 3):
                yield hop, (vid * 7 + hop) % 25

    spark.udtf.register("dyngraph_walk", Walk)
    table(spark, d, "nation", "n_nationkey").createOrReplaceTempView("_walk_nations")
    return spark.sql("SELECT n_nationkey AS vid, w.hop, w.next FROM _walk_nations, LATERAL dyngraph_walk(n_nationkey) w")


@query("SELECT vec_id, round(list_inner_product(CAST(embedding AS DOUBLE[]), CAST(embedding AS DOUBLE[])), 5) AS n2 FROM embeddings")
def u_sql_function(spark: SparkSession, d: str) -> DataFrame:
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vec_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)")
    table(spark, d, "embeddings", "vec_id", "embedding").createOrReplaceTempView("_vec_dot")
    return spark.sql("SELECT vec_id, round(vec_dot(CAST(embedding AS ARRAY<DOUBLE>), CAST(embedding AS ARRAY<DOUBLE>)), 5) AS n2 FROM _vec_dot")


@query("SELECT count(*) AS edges FROM (SELECT DISTINCT o_custkey, o_orderkey FROM orders)")
def u_data_source(spark: SparkSession, d: str) -> DataFrame:
    """Edge lists as text through a reader of our own, one partition a file."""
    from ..sources import edgelist
    from ..sources.tables import scratch_path

    spark.dataSource.register(edgelist.EdgeListSource)
    path = scratch_path(spark, "edgelist")
    graphs.buy(spark, d).select(F.concat_ws(" ", "x", "y", "snap").alias("value")).write.text(path)
    files = [r["path"] for r in spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select("path").collect()]  # names only
    return materialise(spark.read.format("edgelist").option("paths", ",".join(files)).load(), "read").agg(F.count(F.lit(1)).alias("edges"))
