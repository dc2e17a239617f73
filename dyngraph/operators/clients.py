"""What each client holds, and what only the coordinator knows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.graphs import symmetric


def placed(edges: DataFrame, assignment: DataFrame) -> DataFrame:
    """Both directions of each edge with the clients of its ends (src, dst, first, pu, pv)."""
    a = assignment.select("vid", "part")
    both = symmetric(edges)
    both = both.join(a.select(F.col("vid").alias("src"), F.col("part").alias("pu")), "src")
    return both.join(a.select(F.col("vid").alias("dst"), F.col("part").alias("pv")), "dst").select("src", "dst", "first", "pu", "pv")


def local(ee: DataFrame) -> DataFrame:
    return ee.filter("pu = pv")


def cut(ee: DataFrame) -> DataFrame:
    """Cut edges in both directions: dst is a remote neighbour of src."""
    return ee.filter("pu <> pv")


def border(ee: DataFrame) -> DataFrame:
    return cut(ee).select(F.col("src").alias("vid"), F.col("pu").alias("part")).distinct()


def remote_neighbours(ee: DataFrame) -> DataFrame:
    """Size of each border vertex's remote neighbourhood."""
    return cut(ee).groupBy(F.col("src").alias("vid")).agg(F.count(F.lit(1)).alias("remote"))


def cover_faults(vertices: DataFrame, assignment: DataFrame) -> DataFrame:
    """Vertices with other than exactly one client; empty for a disjoint cover."""
    n = assignment.groupBy("vid").agg(F.count(F.lit(1)).alias("clients"))
    return vertices.join(n, "vid", "full").filter("clients is null or clients <> 1").select("vid", F.coalesce("clients", F.lit(0)).cast("long").alias("clients"))
