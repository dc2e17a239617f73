"""Measures of a partition: cut, balance, label entropy, spread over clients, replicas, exactness."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def cut_ratio(ee: DataFrame, by: str | None = None) -> DataFrame:
    """Share of undirected edges between clients (ee holds both directions); by snapshot if asked."""
    one = ee.filter("src < dst")
    out = (one.groupBy(by) if by else one.groupBy()).agg(F.count(F.lit(1)).alias("edges"), F.count_if(F.col("pu") != F.col("pv")).alias("cut"))
    return out.withColumn("ratio", F.round(F.col("cut") / F.col("edges"), 6))


def cut_by_snapshot(ee: DataFrame, last: int) -> DataFrame:
    """Cut ratio of every cumulative snapshot up to ``last``, from counts by first snapshot."""
    counts = cut_ratio(ee, "first").select(F.col("first").alias("snap"), "edges", "cut")
    every = ee.sparkSession.range(last + 1).select(F.col("id").cast("int").alias("snap")).join(F.broadcast(counts), "snap", "left")
    upto = Window.orderBy("snap").rowsBetween(Window.unboundedPreceding, 0)  # one row a snapshot
    out = every.select("snap", F.sum(F.coalesce("edges", F.lit(0))).over(upto).alias("edges"), F.sum(F.coalesce("cut", F.lit(0))).over(upto).alias("cut"))
    return out.withColumn("ratio", F.round(F.col("cut") / F.col("edges"), 6))


def variation(counts: DataFrame, column: str, m: int, by: str) -> DataFrame:
    """Population deviation over mean of a count over all m clients, empty ones included, for each value of ``by``."""
    parts = counts.sparkSession.range(m).select(F.col("id").cast("int").alias("part"))
    grid = counts.select(by).distinct().join(F.broadcast(parts))
    full = grid.join(counts, [by, "part"], "left").fillna(0, [column])
    return full.groupBy(by).agg(F.round(F.stddev_pop(column) / F.avg(column), 6).alias("cov"))


def entropy(assigned: DataFrame, labels: DataFrame) -> DataFrame:
    """(part, n, entropy): base-2 entropy of the classes of each client's labelled vertices."""
    counts = assigned.join(labels, "vid").groupBy("part", "y").agg(F.count(F.lit(1)).alias("n"))
    share = F.col("n") / F.sum("n").over(Window.partitionBy("part"))  # at most one row a class
    return counts.select("part", "n", share.alias("p")).groupBy("part").agg(F.sum("n").alias("n"), F.round(-F.sum(F.col("p") * F.log2("p")), 6).alias("entropy"))


def best_entropy(labels: DataFrame) -> DataFrame:
    return labels.agg(F.count_distinct("y").alias("classes")).select("classes", F.round(F.log2("classes"), 6).alias("best"))


def spread(accuracies: DataFrame, column: str = "accuracy") -> DataFrame:
    """One row: variance, quartiles, interquartile range, and how many clients lie 1.5 of it outside the quartiles."""
    q = accuracies.agg(F.var_pop(column).alias("variance"), F.percentile(column, F.lit(0.25)).alias("q1"), F.percentile(column, F.lit(0.5)).alias("median"), F.percentile(column, F.lit(0.75)).alias("q3"))
    q = q.withColumn("iqr", F.col("q3") - F.col("q1"))
    outside = accuracies.join(F.broadcast(q)).agg(F.count_if((F.col(column) < F.col("q1") - 1.5 * F.col("iqr")) | (F.col(column) > F.col("q3") + 1.5 * F.col("iqr"))).alias("outliers"))
    return q.join(F.broadcast(outside)).select(*[F.round(c, 6).alias(c) for c in ("variance", "q1", "median", "q3", "iqr")], "outliers")


def replicas(copies: DataFrame) -> DataFrame:
    """Copies per vertex of a placement that may repeat vertices, and the largest client against the mean."""
    sizes = copies.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    total = copies.agg(F.count(F.lit(1)).alias("copies"), F.count_distinct("vid").alias("vertices"))
    load = sizes.agg(F.round(F.max("n") / F.avg("n"), 6).alias("imbalance"))
    return total.join(F.broadcast(load)).select("copies", "vertices", F.round(F.col("copies") / F.col("vertices"), 6).alias("factor"), "imbalance")


def residual(got: DataFrame, want: DataFrame) -> DataFrame:
    """One row: vertices, how many differ from the truth in any component, the largest difference."""
    both = want.select("vid", F.col("x").alias("w")).join(got.select("vid", F.col("x").alias("g")), "vid", "left")
    diff = F.coalesce(F.array_max(F.zip_with("w", "g", lambda a, b: F.abs(a - b).cast("double"))), F.array_max(F.transform("w", lambda a: F.abs(a).cast("double"))))
    return both.select(diff.alias("d")).agg(F.count(F.lit(1)).alias("vertices"), F.count_if(F.col("d") > 1e-9).alias("wrong"), F.max("d").alias("largest"))
