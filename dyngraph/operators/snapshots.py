"""Snapshots and deltas as filters over one long table, never as a list of copies."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def window_of(ts: str, days: int, origin: str) -> Column:
    """Number of the calendar window of ``days`` days since ``origin``."""
    return F.floor(F.datediff(F.to_date(ts), F.lit(origin).cast("date")) / days).cast("int")


def cumulative(events: DataFrame) -> DataFrame:
    """Edges with their first snapshot; snapshot t is ``first <= t``."""
    return events.groupBy("src", "dst").agg(F.min("snap").alias("first"))


def sliding(events: DataFrame, width: int) -> DataFrame:
    """Edges with validity [since, until]: an event keeps its edge for ``width`` snapshots; meeting stretches are one."""
    order = Window.partitionBy("a", "b").orderBy("snap")
    marked = events.select("a", "b", "snap").distinct().withColumn("fresh", (F.col("snap") > F.coalesce(F.lag("snap").over(order), F.lit(-(10**9))) + width).cast("int"))
    numbered = marked.withColumn("island", F.sum("fresh").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    return numbered.groupBy("a", "b", "island").agg(F.min("snap").alias("since"), (F.max("snap") + width - 1).alias("until")).select("a", "b", "since", "until")


def at(edges: DataFrame, t: int) -> DataFrame:
    """Snapshot t of cumulative or sliding edges."""
    return edges.filter(F.col("first") <= t) if "first" in edges.columns else edges.filter(F.lit(t).between(F.col("since"), F.col("until")))


def delta(edges: DataFrame, t: int) -> DataFrame:
    """Edges that come (+) or go (-) between t - 1 and t."""
    if "first" in edges.columns:
        return edges.filter(F.col("first") == t).select("a", "b", F.lit("+").alias("op"))
    now, then = at(edges, t).select("a", "b"), at(edges, t - 1).select("a", "b")
    return now.join(then, ["a", "b"], "left_anti").withColumn("op", F.lit("+")).unionAll(then.join(now, ["a", "b"], "left_anti").withColumn("op", F.lit("-")))


def changed(before: DataFrame, after: DataFrame) -> DataFrame:
    """Vertices whose feature differs, null-safe, among those present in both (vid, x)."""
    both = before.select("vid", F.col("x").alias("x0")).join(after.select("vid", F.col("x").alias("x1")), "vid")
    return both.filter(~F.col("x0").eqNullSafe(F.col("x1"))).select("vid")


def arrivals(edges: DataFrame) -> DataFrame:
    """Vertices with the snapshot in which they first have an edge."""
    ends = edges.select(F.col("a").alias("vid"), "first").unionAll(edges.select("b", "first"))
    return ends.groupBy("vid").agg(F.min("first").alias("first"))
