"""Partitioners to compare with: hash, label skew, time slices, modularity communities, multilevel minimum cut."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.graphs import key_of, vertices
from ..sources.tables import materialise


def by_hash(v: DataFrame, m: int) -> DataFrame:
    return v.select("vid", F.pmod(key_of("vid"), F.lit(m)).cast("int").alias("part"))


def draw(v: str, seed: str, n: int):
    """Deterministic number below n from the MD5 of id and seed; DuckDB can repeat it."""
    return F.pmod(F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.col(v).cast("string"))), 1, 13), 16, 10).cast("long"), F.lit(n))


def label_skew(labels: DataFrame, m: int, skew: int = 80) -> DataFrame:
    """Class y lives in client y mod m; ``skew`` of 100 of its vertices go there, the others anywhere."""
    home = F.pmod("y", F.lit(m))
    return labels.select("vid", F.when(draw("vid", "stay", 100) < skew, home).otherwise(draw("vid", "part", m)).cast("int").alias("part"))


def by_time(e: DataFrame, m: int, last: int) -> DataFrame:
    """(vid, part): a copy of each vertex in every time slice in which it has an edge."""
    slice_ = F.floor(F.col("first") * m / (last + 1)).cast("int")
    return e.select(F.col("a").alias("vid"), slice_.alias("part")).unionAll(e.select("b", slice_)).distinct()


def packed(groups: DataFrame, m: int) -> DataFrame:
    """(label, part): groups (label, size) dealt to clients in order of size, back and forth."""
    order = Window.partitionBy("bucket").orderBy(F.desc("size"), "label")
    g = groups.withColumn("bucket", F.floor(F.log2(F.greatest("size", F.lit(1)))).cast("int"))
    g = g.withColumn("n", F.row_number().over(order) - 1 + F.col("bucket"))
    turn = F.pmod("n", F.lit(2 * m))
    return g.select("label", F.least(turn, 2 * m - 1 - turn).cast("int").alias("part"))


def weighted(e: DataFrame) -> DataFrame:
    return e.select("a", "b", F.lit(1).cast("long").alias("w"))


def modularity_value(e: DataFrame, label: DataFrame) -> DataFrame:
    """One row q: share of edges inside groups minus what degrees alone would give."""
    m = e.agg(F.count(F.lit(1)).alias("m")).select("m").scalar()
    la = e.join(label.select(F.col("vid").alias("a"), F.col("label").alias("la")), "a").join(label.select(F.col("vid").alias("b"), F.col("label").alias("lb")), "b")
    inside = la.filter("la = lb").groupBy(F.col("la").alias("label")).agg(F.count(F.lit(1)).alias("inside"))
    ends = la.select(F.col("la").alias("label")).unionAll(la.select("lb")).groupBy("label").agg(F.count(F.lit(1)).alias("ends"))
    both = ends.join(inside, "label", "left")
    return both.agg(F.round(F.sum(F.coalesce("inside", F.lit(0)) / m - (F.col("ends") / (2 * m)) ** 2), 6).alias("q"))


def _moves(e: DataFrame, label: DataFrame, parity: int) -> DataFrame:
    """(vid, label): best gain in modularity among neighbours' groups, for vertices of one parity."""
    both = e.select("a", "b", "w").unionAll(e.select("b", "a", "w")).toDF("v", "u", "w")
    total = e.agg(F.sum("w").alias("t")).select("t").scalar()
    deg = both.groupBy("v").agg(F.sum("w").alias("k"))
    group = deg.join(label.withColumnRenamed("vid", "v"), "v").groupBy("label").agg(F.sum("k").alias("vol"))
    near = both.filter(F.pmod(F.xxhash64("v"), F.lit(2)) == parity).filter("v <> u").join(label.select(F.col("vid").alias("u"), "label"), "u").groupBy("v", "label").agg(F.sum("w").alias("w"))
    own = label.withColumnRenamed("vid", "v").withColumnRenamed("label", "now")
    cand = near.join(own, "v").join(deg, "v").join(group, "label")
    cand = cand.withColumn("gain", F.col("w") - F.col("k") * (F.col("vol") - F.when(F.col("label") == F.col("now"), F.col("k")).otherwise(0)) / (2.0 * total))
    stay = cand.filter("label = now").select("v", F.col("gain").alias("g0"))
    best = cand.groupBy("v").agg(F.max_by(F.struct("label", "gain", "now"), F.struct("gain", -F.col("label"))).alias("m")).join(stay, "v", "left")
    return best.filter("m.label <> m.now and m.gain > coalesce(g0, 0) + 1e-9").select(F.col("v").alias("vid"), F.col("m.label").alias("to"))


def modularity(e: DataFrame, passes: int = 3, rounds: int = 4) -> DataFrame:
    """(vid, label): local moves by alternating halves, then contraction, a few passes."""
    work = materialise(weighted(e), "graph")
    found = materialise(vertices(e).select("vid", F.col("vid").alias("label")), "labels")
    for _ in range(passes):
        nodes = work.select(F.col("a").alias("vid")).unionAll(work.select("b")).distinct()
        label = materialise(nodes.select("vid", F.col("vid").alias("label")), "labels")
        moved = False
        for r in range(rounds):
            moves = materialise(_moves(work, label, r % 2), "moves")
            if moves.isEmpty():
                continue
            moved = True
            label = materialise(label.join(moves, "vid", "left").select("vid", F.coalesce("to", "label").alias("label")), "labels")
        if not moved:
            break
        found = materialise(found.join(label.select(F.col("vid").alias("label"), F.col("label").alias("to")), "label", "left").select("vid", F.coalesce("to", "label").alias("label")), "labels")
        la = work.join(label.select(F.col("vid").alias("a"), F.col("label").alias("la")), "a").join(label.select(F.col("vid").alias("b"), F.col("label").alias("lb")), "b")
        work = materialise(la.groupBy(F.least("la", "lb").alias("a"), F.greatest("la", "lb").alias("b")).agg(F.sum("w").alias("w")), "graph")
    return found


def communities(e: DataFrame, m: int) -> DataFrame:
    """(vid, part): modularity groups packed into m clients."""
    label = modularity(e)
    part = packed(label.groupBy("label").agg(F.count(F.lit(1)).alias("size")), m)
    return label.join(part, "label").select("vid", "part")


def matching(e: DataFrame) -> DataFrame:
    """(a, b): edges that both ends hold for their heaviest (smallest partner among equals)."""
    both = e.select("a", "b", "w").unionAll(e.select("b", "a", "w")).toDF("v", "u", "w").filter("v <> u")
    best = both.groupBy("v").agg(F.max_by("u", F.struct("w", -F.col("u"))).alias("u"))
    return best.join(best.select(F.col("v").alias("u"), F.col("u").alias("v")), ["v", "u"]).filter("v < u").select(F.col("v").alias("a"), F.col("u").alias("b"))


def _solve(nodes: pd.DataFrame, edges: pd.DataFrame, m: int, slack: float) -> np.ndarray:
    """Greedy growth of m balanced parts in one task, on a graph of bounded size; heaviest vertices first."""
    ids = nodes["vid"].to_numpy()
    size = nodes["size"].to_numpy(np.float64)
    at = {v: i for i, v in enumerate(ids)}
    near: list[list[tuple[int, float]]] = [[] for _ in ids]
    for a, b, w in edges[["a", "b", "w"]].itertuples(index=False):
        if a != b:
            near[at[a]].append((at[b], w))
            near[at[b]].append((at[a], w))
    cap = (1 + slack) * size.sum() / m
    part, load = np.full(len(ids), -1), np.zeros(m)
    for v in np.lexsort((ids, -size)):
        pull = np.zeros(m)
        for u, w in near[v]:
            if part[u] >= 0:
                pull[part[u]] += w
        fits = load + size[v] <= cap
        order = sorted(range(m), key=lambda p: (not fits[p], -pull[p] if fits[p] else 0.0, load[p], p))  # noqa: B023
        part[v] = order[0]
        load[order[0]] += size[v]
    return part


def multilevel(e: DataFrame, m: int, slack: float = 0.1, coarse: int = 2_000, max_levels: int = 12, rounds: int = 2) -> DataFrame:
    """(vid, part): matched and contracted until ``coarse`` vertices, solved in one task, projected and refined.

    If matching stalls above the bound, the remaining vertices are grouped by hash so that the one task stays bounded.
    """
    work = materialise(weighted(e), "graph")
    size = materialise(vertices(e).select("vid", F.lit(1).cast("long").alias("size")), "sizes")
    maps: list[DataFrame] = []
    for _ in range(max_levels):
        n = size.count()
        if n <= coarse:
            break
        pairs = matching(work)
        to = materialise(size.select("vid").join(pairs.select(F.col("b").alias("vid"), F.col("a").alias("to")), "vid", "left").select("vid", F.coalesce("to", "vid").alias("to")), "levels")
        size = materialise(size.join(to, "vid").groupBy(F.col("to").alias("vid")).agg(F.sum("size").alias("size")), "sizes")
        stalled = size.count() > 0.95 * n
        if stalled and n > 4 * coarse:
            into = size.select(F.col("vid").alias("to"), F.pmod(F.xxhash64("vid"), F.lit(coarse)).alias("into"))
            size = materialise(size.join(into.withColumnRenamed("to", "vid"), "vid").groupBy(F.col("into").alias("vid")).agg(F.sum("size").alias("size")), "sizes")
            to = materialise(to.join(into, "to").select("vid", F.col("into").alias("to")), "levels")  # after the matching
        maps.append(to)
        la = work.join(to.select(F.col("vid").alias("a"), F.col("to").alias("la")), "a").join(to.select(F.col("vid").alias("b"), F.col("to").alias("lb")), "b")
        work = materialise(la.filter("la <> lb").groupBy(F.least("la", "lb").alias("a"), F.greatest("la", "lb").alias("b")).agg(F.sum("w").alias("w")), "graph")
        if stalled:
            break
    one = F.lit(0).alias("g")

    def solve(nodes: pd.DataFrame, edges: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"vid": nodes["vid"], "part": _solve(nodes, edges, m, slack)})

    part = size.select(one, "*").groupBy("g").cogroup(work.select(one, "*").groupBy("g")).applyInPandas(solve, "vid long, part int")
    for to in reversed(maps):
        part = to.join(part.withColumnRenamed("vid", "to"), "to").select("vid", "part")
    part = materialise(part, "parts")
    both = e.select("a", "b").unionAll(e.select("b", "a")).toDF("v", "u")
    for r in range(rounds):  # move where a strict majority of neighbours is, within the bound on size
        sizes = part.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
        total = part.count()
        near = both.join(part.select(F.col("vid").alias("u"), "part"), "u").groupBy("v", "part").agg(F.count(F.lit(1)).alias("w"))
        now = part.select(F.col("vid").alias("v"), F.col("part").alias("now")).filter(F.pmod(F.xxhash64("v"), F.lit(2)) == r % 2)
        best = near.join(now, "v").join(F.broadcast(sizes), "part").filter((F.col("part") == F.col("now")) | (F.col("n") < (1 + slack) * total / m))
        best = best.groupBy("v").agg(F.max_by("part", F.struct("w", (F.col("part") == F.col("now")).cast("int"), -F.col("part"))).alias("to"))
        part = materialise(part.join(best.select(F.col("v").alias("vid"), "to"), "vid", "left").select("vid", F.coalesce("to", "part").alias("part")), "parts")
    return part
