"""What a client can see and infer, as checks on produced tables."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import clients
from ..operators.primitives import components


def client_view(ee: DataFrame, assigned: DataFrame, outbox: DataFrame, m: int) -> dict[str, DataFrame]:
    """All that client m may read: its vertices, its inner edges, its messages."""
    return {
        "vertices": assigned.filter(F.col("part") == m).select("vid"),
        "edges": clients.local(ee).filter(F.col("pu") == m).select("src", "dst", "first"),
        "messages": outbox.filter(F.col("part") == m).select("snap", "vid", "hop", "x"),
    }


def oblivious_faults(outbox: DataFrame, assigned: DataFrame) -> DataFrame:
    """Messages to a client about a vertex that it does not own; empty when nothing leaks."""
    return outbox.join(assigned.select("vid", "part"), ["vid", "part"], "left_anti").select("part", "vid", "hop")


def ambiguity(ee: DataFrame) -> DataFrame:
    """(remote, vertices): how many border vertices have so many remote neighbours."""
    return clients.remote_neighbours(ee).groupBy("remote").agg(F.count(F.lit(1)).alias("vertices"))


def singletons(ee: DataFrame) -> DataFrame:
    """One row: border vertices, those with a single remote neighbour (whose feature a message hands over), the share."""
    out = clients.remote_neighbours(ee).agg(F.count(F.lit(1)).alias("border"), F.count_if(F.col("remote") == 1).alias("singletons"))
    return out.withColumn("share", F.round(F.col("singletons") / F.col("border"), 6))


def irreversibility(pre: DataFrame, degrees: DataFrame) -> DataFrame:
    """One row: share of pre-activations that a rectifier clips, and of vertices that mix more than one neighbour."""
    clipped = pre.select(F.explode("x").alias("z")).agg(F.round(F.avg((F.col("z") <= 0).cast("int")), 6).alias("clipped"))
    mixed = degrees.agg(F.round(F.avg((F.col("deg") > 1).cast("int")), 6).alias("mixing"))
    return clipped.join(F.broadcast(mixed))


def collusion(ee: DataFrame, colluders: list[int]) -> DataFrame:
    """One row: border vertices of the colluders (equations a dimension) against distinct remote neighbours outside (unknowns)."""
    c = clients.cut(ee).filter(F.col("pu").isin(colluders) & ~F.col("pv").isin(colluders))
    return c.agg(F.count_distinct("src").alias("equations"), F.count_distinct("dst").alias("unknowns")).withColumn("underdetermined", F.col("unknowns") > F.col("equations"))


def dimension(ee: DataFrame, assigned: DataFrame, d: int) -> DataFrame:
    """(part, border, received, pairs, holds): numbers a client gets against the vertex pairs of all other clients."""
    b = clients.border(ee).groupBy("part").agg(F.count(F.lit(1)).alias("border"))
    sizes = assigned.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    pairs = sizes.select("part", (F.col("n") * (F.col("n") - 1) / 2).cast("long").alias("pairs"))
    total = pairs.agg(F.sum("pairs").alias("t")).select("t").scalar()
    out = pairs.join(b, "part", "left").select("part", F.coalesce("border", F.lit(0)).alias("border"), (total - F.col("pairs")).alias("pairs"))
    return out.withColumn("received", 2 * F.col("border") * d).withColumn("holds", F.col("received") < F.col("pairs")).select("part", "border", "received", "pairs", "holds")


def attack(ee: DataFrame, feats: DataFrame, colluders: list[int], max_unknowns: int = 400) -> DataFrame:
    """(piece, equations, unknowns, rank, recovered): least squares on pooled one-hop sums, piece by piece.

    Pieces are the components of the border's bipartite graph; those beyond ``max_unknowns`` vertices are reported
    with rank null, since solving them is not one task's work.
    """
    c = clients.cut(ee).filter(F.col("pu").isin(colluders) & ~F.col("pv").isin(colluders)).select("src", "dst")
    label = components(c.select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")))
    rows = c.join(label.select(F.col("vid").alias("src"), F.col("label").alias("piece")), "src").join(feats.select(F.col("vid").alias("dst"), F.col("x")[0].cast("double").alias("x")), "dst")
    sizes = rows.groupBy("piece").agg(F.count_distinct("src").alias("equations"), F.count_distinct("dst").alias("unknowns"))
    small = rows.join(sizes.filter((F.col("unknowns") <= max_unknowns) & (F.col("equations") <= 4 * max_unknowns)), "piece")

    def solve(g: pd.DataFrame) -> pd.DataFrame:
        s, t = pd.factorize(g["src"])[0], pd.factorize(g["dst"])[0]
        a = np.zeros((s.max() + 1, t.max() + 1))
        a[s, t] = 1.0
        x = np.zeros(t.max() + 1)
        x[t] = g["x"]
        guess = np.linalg.lstsq(a, a @ x, rcond=None)[0]
        return pd.DataFrame({"piece": [g["piece"].iloc[0]], "rank": [int(np.linalg.matrix_rank(a))], "recovered": [int((np.abs(guess - x) < 1e-6).sum())]})

    solved = small.select("piece", "src", "dst", "x").groupBy("piece").applyInPandas(solve, "piece long, rank long, recovered long")
    return sizes.join(solved, "piece", "left")
