"""Graph primitives: degrees, components, breadth-first levels, neighbourhood scores."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.graphs import symmetric, vertices
from ..sources.tables import materialise


def degrees(e: DataFrame) -> DataFrame:
    return symmetric(e.select("a", "b", F.lit(0).alias("first"))).groupBy(F.col("src").alias("vid")).agg(F.count(F.lit(1)).alias("deg"))


def components(e: DataFrame, max_rounds: int = 64) -> DataFrame:
    """(vid, label): smallest vertex of the component, isolated vertices not included.

    A round points each vertex at its smallest neighbour, shortens the pointers twice and contracts the edges, whose
    vertices at least halve; only emptiness is asked for by the driver.
    """
    left = materialise(e.filter("a <> b").select("a", "b").distinct(), "edges")
    found = materialise(vertices(left).select("vid", F.col("vid").alias("label")), "labels")
    for _ in range(max_rounds):
        if left.isEmpty():
            break
        both = left.unionAll(left.select("b", "a"))
        to = both.groupBy(F.col("a").alias("v")).agg(F.least(F.min("a"), F.min("b")).alias("p"))
        for _ in range(2):
            to = to.join(to.select(F.col("v").alias("p"), F.col("p").alias("q")), "p", "left").select("v", F.coalesce("q", "p").alias("p"))
        to = materialise(to, "pointers")
        found = materialise(found.join(to.select(F.col("v").alias("label"), "p"), "label", "left").select("vid", F.coalesce("p", "label").alias("label")), "labels")
        left = left.join(to.select(F.col("v").alias("a"), F.col("p").alias("pa")), "a").join(to.select(F.col("v").alias("b"), F.col("p").alias("pb")), "b")
        left = materialise(left.filter("pa <> pb").select(F.least("pa", "pb").alias("a"), F.greatest("pa", "pb").alias("b")).distinct(), "edges")
    return found


def levels(e: DataFrame, start: DataFrame, max_level: int = 10**6) -> DataFrame:
    """(vid, level): breadth-first distance from any of the start vertices, for those reached.

    A neighbour of a frontier lies in it, in the one before or in the next, so a round joins these alone and its plan
    stays the same; the frontiers are brought together every few rounds.
    """
    both = materialise(symmetric(e.select("a", "b", F.lit(0).alias("first"))).select("src", "dst"), "both")
    found = frontier = materialise(start.select("vid", F.lit(0).alias("level")).distinct(), "levels")
    before = frontier.limit(0)
    for level in range(1, max_level + 1):
        step = both.join(frontier.select(F.col("vid").alias("src")), "src").select(F.col("dst").alias("vid")).distinct()
        near = frontier.select("vid").unionAll(before.select("vid"))
        before, frontier = frontier, materialise(step.join(near, "vid", "left_anti").select("vid", F.lit(level).alias("level")), "frontier")
        if frontier.isEmpty():
            break
        found = found.unionAll(frontier)
        if level % 16 == 0:
            found = materialise(found, "levels")
    return found


def common_neighbours(e: DataFrame) -> DataFrame:
    """(u, v, common, jaccard, adamic_adar) for pairs u < v with a common neighbour."""
    both = symmetric(e.select("a", "b", F.lit(0).alias("first"))).select("src", "dst")
    deg = degrees(e)
    near = both.join(deg.withColumnRenamed("vid", "dst"), "dst")
    pairs = near.select(F.col("src").alias("u"), "dst", "deg").join(both.select(F.col("src").alias("v"), "dst"), "dst").filter("u < v")
    out = pairs.groupBy("u", "v").agg(F.count(F.lit(1)).alias("common"), F.sum(F.lit(1.0) / F.log(F.greatest("deg", F.lit(2)))).alias("adamic_adar"))
    out = out.join(deg.select(F.col("vid").alias("u"), F.col("deg").alias("du")), "u").join(deg.select(F.col("vid").alias("v"), F.col("deg").alias("dv")), "v")
    return out.select("u", "v", "common", F.round(F.col("common") / (F.col("du") + F.col("dv") - F.col("common")), 6).alias("jaccard"), F.round("adamic_adar", 6).alias("adamic_adar"))


def triangles(e: DataFrame) -> DataFrame:
    """Triangles of the graph as (x < y < z): edges towards the larger (degree, id) end, so hubs list few pairs."""
    deg = degrees(e)
    w = e.select("a", "b").join(deg.select(F.col("vid").alias("a"), F.col("deg").alias("da")), "a").join(deg.select(F.col("vid").alias("b"), F.col("deg").alias("db")), "b")
    up = F.struct("da", "a") < F.struct("db", "b")
    out = w.select(F.when(up, F.col("a")).otherwise(F.col("b")).alias("s"), F.when(up, F.col("b")).otherwise(F.col("a")).alias("t"))
    wedge = out.join(out.select("s", F.col("t").alias("t2")), "s").filter("t < t2")
    return wedge.join(e.select(F.col("a").alias("t"), F.col("b").alias("t2")), ["t", "t2"], "left_semi").select(F.sort_array(F.array("s", "t", "t2")).alias("v")).select(*[F.get("v", F.lit(i)).alias(c) for i, c in enumerate("xyz")])
