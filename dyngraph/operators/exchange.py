"""Embedding exchange through the coordinator: what each vertex lacks over one and two hops.

With c the cut and l the local adjacency, x the features and H1 the local sums (self included), the corrections are
d1 = c.x and, complete, d2 = c.(H1 + d1) + d1 + l.d1. The printed variants leave out l.d1, and the plain printed one
also adds each vertex's own feature once per cut edge. Sums are taken before joins, so no two-step path is listed.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import summed, width
from ..sources.tables import materialise
from . import clients, message

MODES = ("complete", "printed", "printed_excl_self")


def pulled(pairs: DataFrame, h: DataFrame, d: int) -> DataFrame:
    """Sum of h over the dst of each src."""
    return summed(pairs.select("src", "dst").join(h.select(F.col("vid").alias("dst"), "x"), "dst").select(F.col("src").alias("vid"), "x"), "vid", d)


def hop1(ee: DataFrame, feats: DataFrame, region: DataFrame | None = None, d: int | None = None) -> DataFrame:
    """One-hop corrections; ``region`` restricts the receivers below the aggregation."""
    c = clients.cut(ee)
    if region is not None:
        c = c.join(region.select(F.col("vid").alias("src")).distinct(), "src", "left_semi")
    return pulled(c, feats, d or width(feats))


def hop2(ee: DataFrame, feats: DataFrame, mode: str = "complete", region: DataFrame | None = None, d: int | None = None) -> DataFrame:
    """Two-hop corrections. With a region, d1 and H1 are still taken over its halo, where they come from."""
    if mode not in MODES:
        raise ValueError(f"unknown mode {mode!r}")
    d = d or width(feats)
    d1 = hop1(ee, feats, d=d)
    h1 = message.aggregate(clients.local(ee), feats, "sum", d=d)
    only = (lambda df, c: df.join(region.select(F.col("vid").alias(c)).distinct(), c, "left_semi")) if region is not None else (lambda df, c: df)
    cut, local = only(clients.cut(ee), "src"), only(clients.local(ee), "src")
    parts = [pulled(cut, message.with_own(h1, d1), d), only(d1, "vid")]
    if mode == "complete":
        parts.append(pulled(local, d1, d))
    if mode == "printed":
        degree = cut.groupBy(F.col("src").alias("vid")).agg(F.count(F.lit(1)).alias("n"))
        parts.append(feats.join(degree, "vid").select("vid", F.transform("x", lambda v: v * F.col("n")).alias("x")))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionAll(p)
    return summed(out, "vid", d)


def apply(local: DataFrame, corrections: DataFrame) -> DataFrame:
    """Local state plus correction; vertices without a message unchanged."""
    return message.with_own(local, corrections)


def local_states(ee: DataFrame, feats: DataFrame, hops: int, d: int | None = None) -> DataFrame:
    """What the clients compute by themselves."""
    h = feats
    for _ in range(hops):
        h = message.aggregate(clients.local(ee), h, "sum", d=d)
    return h


def truth(ee: DataFrame, feats: DataFrame, hops: int, d: int | None = None) -> DataFrame:
    """The same sums over the whole graph."""
    h = feats
    for _ in range(hops):
        h = message.aggregate(ee, h, "sum", d=d)
    return h


def feature_sum(ee: DataFrame, feats: DataFrame, contrib: str = "owner", d: int | None = None) -> DataFrame:
    """Baseline: input features replaced by sums that the clients contribute.

    ``owner``: every client sums the features of its vertices next to i, whoever owns i, and the coordinator adds them
    up. ``literal``: clients sum over neighbours inside themselves only.
    """
    pairs = {"owner": ee, "literal": clients.local(ee)}[contrib]
    return message.aggregate(pairs, feats, "sum", d=d)


def layerwise(ee: DataFrame, feats: DataFrame, weights: list, act: str = "relu", d: int | None = None) -> DataFrame:
    """Exact for any weight and activation: the sum before each layer is corrected with the remote states of that layer."""
    h = feats
    for w in weights:
        z = message.aggregate(clients.local(ee), h, "sum", d=d)
        z = message.with_own(z, pulled(clients.cut(ee), h, d or width(h)))
        h = message.dense_sql(z, w, act)
        d = len(w[0])
    return h


@dataclass(frozen=True)
class Schedule:
    """When to exchange: in the first or last epoch, of all rounds, the first one or the middle one."""

    epoch: str = "last"
    rounds: str = "first"

    def fires(self, epoch: int, r: int, epochs: int, rounds: int) -> bool:
        at = {"first": 1, "last": epochs}[self.epoch]
        return epoch == at and {"all": True, "first": r == 1, "mid": r == -(-rounds // 2)}[self.rounds]

    def firings(self, epochs: int, rounds: int) -> int:
        return sum(self.fires(e, r, epochs, rounds) for r in range(1, rounds + 1) for e in range(1, epochs + 1))


SCHEDULES = (Schedule("first", "all"), Schedule("last", "all"), Schedule("last", "first"), Schedule("last", "mid"))


def submit(ee: DataFrame, feats: DataFrame, d: int | None = None) -> DataFrame:
    """Inbox: the 0-hop and local 1-hop states of border vertices (part, vid, hop, x)."""
    b = clients.border(ee)
    h1 = message.aggregate(clients.local(ee), feats, "sum", d=d)
    zero = b.join(feats, "vid").select("part", "vid", F.lit(0).alias("hop"), "x")
    return zero.unionAll(b.join(h1, "vid").select("part", "vid", F.lit(1).alias("hop"), "x"))


def outbox(ee: DataFrame, feats: DataFrame, assignment: DataFrame, snap: int, hops: int = 2, mode: str = "complete", region: DataFrame | None = None, min_group: int = 1, d: int | None = None) -> DataFrame:
    """Messages by owner: snap, part, vid, hop, x as floats; nothing names or counts a remote vertex.

    ``min_group`` withholds one-hop sums of fewer contributors. More than two hops are refused.
    """
    if hops > 2:
        raise ValueError("an exchange reaches two hops at most")
    one = hop1(ee, feats, region, d)
    if min_group > 1:
        enough = clients.remote_neighbours(ee).filter(F.col("remote") >= min_group)
        one = one.join(enough, "vid", "left_semi")
    rows = one.select("vid", F.lit(1).alias("hop"), "x")
    if hops == 2:
        rows = rows.unionAll(hop2(ee, feats, mode, region, d).select("vid", F.lit(2).alias("hop"), "x"))
    return rows.join(assignment.select("vid", "part"), "vid").select(F.lit(snap).alias("snap"), "part", "vid", "hop", F.col("x").cast("array<float>").alias("x"))


def protocol(ee: DataFrame, feats: DataFrame, assignment: DataFrame, snap: int, mode: str = "complete", d: int | None = None) -> DataFrame:
    """The four steps: submit, combine, send by owner, add. Inbox and outbox are written tables; returns corrected 2-hop states."""
    materialise(submit(ee, feats, d), "inbox", by="part")
    sent = materialise(outbox(ee, feats, assignment, snap, 2, mode, d=d), "outbox", by="part")
    two = sent.filter("hop = 2").select("vid", F.col("x").cast("array<double>").alias("x"))
    return apply(local_states(ee, feats, 2, d).select("vid", F.col("x").cast("array<double>").alias("x")), two)
