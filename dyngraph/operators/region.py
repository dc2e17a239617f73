"""Seeds and the region that a change reaches."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.graphs import symmetric, vertices
from ..sources.tables import materialise
from .snapshots import arrivals, at, delta


def seeds(edges: DataFrame, t: int, mode: str = "touched", changed: DataFrame | None = None) -> DataFrame:
    """``new_vertices``: those that first appear at t. ``touched``: also ends of edges that came or went, and changed ones."""
    if mode == "new_vertices":
        return arrivals(edges).filter(F.col("first") == t).select("vid")
    if mode != "touched":
        raise ValueError(f"unknown seed mode {mode!r}")
    d = delta(edges, t)
    found = d.select(F.col("a").alias("vid")).unionAll(d.select("b"))
    if changed is not None:
        found = found.unionAll(changed.select("vid"))
    return found.distinct()


def khop(edges: DataFrame, start: DataFrame, k: int) -> DataFrame:
    """(vid, hop) up to k hops from the seeds that have an edge; k unrolled joins of the frontier only."""
    both = symmetric(edges.select("a", "b", F.lit(0).alias("first"))).select("src", "dst")
    found = start.join(vertices(edges), "vid", "left_semi").select("vid", F.lit(0).alias("hop"))
    frontier = found
    for hop in range(1, k + 1):
        step = both.join(frontier.select(F.col("vid").alias("src")), "src").select(F.col("dst").alias("vid")).distinct()
        frontier = step.join(found, "vid", "left_anti").select("vid", F.lit(hop).alias("hop"))
        found = found.unionAll(frontier)
    return found


def induce(edges: DataFrame, region: DataFrame) -> DataFrame:
    """Edges with both ends in the region."""
    v = region.select("vid")
    return edges.join(v, edges.a == v.vid, "left_semi").join(v, F.col("b") == v.vid, "left_semi")


def rings(edges: DataFrame, touched: DataFrame, k: int, changed: DataFrame | None = None) -> DataFrame:
    """(layer, vid): layer l recomputes what lies l - 1 hops from a touched vertex, and layer 1 the neighbours of vertices with a changed feature."""
    start = touched.select("vid")
    if changed is not None:
        both = symmetric(edges.select("a", "b", F.lit(0).alias("first")))
        near = both.join(changed.select(F.col("vid").alias("src")), "src", "left_semi").select(F.col("dst").alias("vid"))
        start = start.unionAll(changed.select("vid")).unionAll(near).distinct()
    reach = khop(edges, start, k - 1)
    layers = edges.sparkSession.range(1, k + 1).select(F.col("id").cast("int").alias("layer"))
    return reach.join(F.broadcast(layers), F.col("hop") < F.col("layer")).select("layer", "vid")


def locality(edges: DataFrame, region: DataFrame) -> DataFrame:
    """One row: vertices, edges, and how many of them lie in the region."""
    v = vertices(edges).agg(F.count(F.lit(1)).alias("vertices"))
    e = edges.agg(F.count(F.lit(1)).alias("edges"))
    r = region.select("vid").distinct().agg(F.count(F.lit(1)).alias("region_vertices"))
    i = induce(edges, region).agg(F.count(F.lit(1)).alias("region_edges"))
    out = v.join(F.broadcast(e)).join(F.broadcast(r)).join(F.broadcast(i))
    return out.withColumn("share", F.round(F.col("region_vertices") / F.col("vertices"), 6))


def chosen(edges: DataFrame, t: int, k: int, full_above: float = 0.5, mode: str = "touched") -> DataFrame:
    """The region of the change at t, or every vertex where the region would hold more than ``full_above`` of them.

    Regions only grow, so no hop is taken once they hold that many.
    """
    now = at(edges, t)
    every = materialise(vertices(now), "vertices")
    whole = every.count()
    found = frontier = materialise(khop(now, seeds(edges, t, mode), 0), "region")
    for hop in range(1, k + 2):
        share = round(found.count() / whole, 6) if whole else 0  # a vertex has one row
        if share > full_above:
            return every.select("vid", F.lit(0).alias("hop"))
        if hop <= k:
            step = khop(now, frontier.select("vid"), 1).filter("hop = 1").select("vid")
            frontier = materialise(step.join(found, "vid", "left_anti").select("vid", F.lit(hop).alias("hop")), "region")
            found = found.unionAll(frontier)
    return found
