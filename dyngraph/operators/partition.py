"""Two-stage vertex partitioner: placed from distant seeds at first, then kept and extended with each snapshot.

Stage one places a vertex by one hard objective; stage two moves it where a weighted score of the other two gains
enough. All scores are relations and all ties are broken by a total order. A round scores every open vertex against
the assignment of the round before; nothing that grows with vertices or edges reaches the driver.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.graphs import key_of, symmetric, vertices
from ..sources.tables import materialise
from .primitives import components, degrees, levels

EPSILON = 1e-9


@dataclass(frozen=True)
class Config:
    """``primary`` is the objective of stage one: cut, balance or label."""

    clients: int = 4
    target: int | None = None  # vertices a client; where set, the number of clients follows the graph
    primary: str = "cut"
    alpha: float = 0.5
    tau: float = 0.01
    max_new_cut: int = 0
    rounds: int = 5
    cap: float = 0.05
    scope: str = "border"  # what stage two may move: conflicts, or conflicting and border vertices
    max_level: int = 64


def client_count(n: int, target: int = 2_000, lo: int = 2, hi: int = 100_000) -> int:
    """Clients for n vertices: grows with the graph, within bounds."""
    return max(lo, min(hi, math.ceil(n / target)))


def is_valid(prev: DataFrame | None, was: int | None, m: int) -> bool:
    """An old partition, made for ``was`` clients, is reused only while the number of clients stays the same."""
    return prev is not None and was == m and not prev.isEmpty()


def sized(e: DataFrame, cfg: Config) -> Config:
    """``cfg`` with the number of clients that the graph asks for."""
    return cfg if cfg.target is None else replace(cfg, clients=client_count(vertices(e).count(), cfg.target))


def part_list(df: DataFrame, m: int) -> DataFrame:
    return df.sparkSession.range(m).select(F.col("id").cast("int").alias("part"))


# --- pieces of the first placement


def stitch(e: DataFrame, labels: DataFrame, buckets: int = 256) -> DataFrame:
    """Synthetic edges (a, b) that join the components in order of size (descending) and label.

    Components are dealt into ``buckets`` by size and label, chained within each, and then the buckets' heads are
    chained; with few components the result is one chain in order.
    """
    rep = labels.join(degrees(e), "vid", "left").groupBy("label").agg(F.count(F.lit(1)).alias("size"), F.max_by("vid", F.struct(F.coalesce("deg", F.lit(0)), -F.col("vid"))).alias("rep"))
    rep = rep.withColumn("bucket", F.when(F.col("size") >= 2**40, 0).otherwise(40 - F.floor(F.log2("size"))).cast("int"))
    order = Window.partitionBy("bucket").orderBy(F.desc("size"), "label")
    chained = rep.withColumn("prev", F.lag("rep").over(order))
    within = chained.filter("prev is not null").select("rep", "prev")
    ends = chained.groupBy("bucket").agg(F.min_by("rep", F.struct(-F.col("size"), "label")).alias("rep"), F.max_by("rep", F.struct(-F.col("size"), "label")).alias("last"))
    across = ends.withColumn("prev", F.lag("last").over(Window.orderBy("bucket"))).filter("prev is not null").select("rep", "prev")  # one row a bucket
    return within.unionAll(across).select(F.least("rep", "prev").alias("a"), F.greatest("rep", "prev").alias("b"))


def first_seed(e: DataFrame) -> DataFrame:
    """The vertex of largest degree, smallest id among equals."""
    return degrees(e).agg(F.max_by("vid", F.struct("deg", -F.col("vid"))).alias("vid"))


def far_seeds(e: DataFrame, m: int) -> list[int]:
    """m vertices, each as far as possible from those before; unreached counts as farthest. One search a seed."""
    all_v = materialise(vertices(e), "vertices")
    seed = first_seed(e).first()["vid"]
    if seed is None:
        return []
    out, dist = [seed], None
    for _ in range(m - 1):
        found = levels(e, all_v.filter(F.col("vid") == out[-1]))
        now = all_v.join(found, "vid", "left").select("vid", F.coalesce("level", F.lit(10**9)).alias("d"))
        dist = now if dist is None else dist.join(now.withColumnRenamed("d", "d2"), "vid").select("vid", F.least("d", "d2").alias("d"))
        dist = materialise(dist, "distances")
        far = dist.agg(F.max_by("vid", F.struct("d", -F.col("vid"))).alias("vid"), F.max("d").alias("d")).first()
        if not far["d"]:
            break
        out.append(far["vid"])
    return out


def reached(both: DataFrame, assigned: DataFrame, open_: DataFrame) -> DataFrame:
    """(vid, owners, part): unowned vertices next to owned ones; part is set where one owner alone reaches them."""
    near = both.join(assigned.select(F.col("vid").alias("src"), "part"), "src").select(F.col("dst").alias("vid"), "part").join(open_.select("vid"), "vid", "left_semi")
    return near.groupBy("vid").agg(F.count_distinct("part").alias("owners"), F.min("part").alias("part"))


# --- scores


def votes(both: DataFrame, v: DataFrame, assigned: DataFrame) -> DataFrame:
    """(vid, part, votes): real neighbours of the vertices of v that are placed already."""
    near = both.join(v.select(F.col("vid").alias("src")).distinct(), "src", "left_semi")
    return near.join(assigned.select(F.col("vid").alias("dst"), "part"), "dst").groupBy(F.col("src").alias("vid"), "part").agg(F.count(F.lit(1)).alias("votes"))


def volumes(both: DataFrame, assigned: DataFrame, m: int) -> DataFrame:
    """(part, vol): edge ends in each client, empty ones included."""
    deg = both.groupBy(F.col("src").alias("vid")).agg(F.count(F.lit(1)).alias("deg"))
    held = assigned.join(deg, "vid").groupBy("part").agg(F.sum("deg").alias("vol"))
    return part_list(both, m).join(held, "part", "left").select("part", F.coalesce("vol", F.lit(0)).cast("long").alias("vol"))


def balance(vol: DataFrame) -> DataFrame:
    """(part, balance): one minus the client's share of edge ends."""
    total = vol.agg(F.sum("vol").alias("t")).select("t").scalar()
    return vol.select("part", (F.lit(1.0) - F.col("vol") / F.greatest(total, F.lit(1))).alias("balance"))


def label_diversity(assigned: DataFrame, labels: DataFrame, m: int) -> DataFrame:
    """(part, y, label_div): one minus the share of label y among the client's labelled vertices."""
    counts = assigned.join(labels, "vid").groupBy("part", "y").agg(F.count(F.lit(1)).alias("n"))
    sizes = counts.groupBy("part").agg(F.sum("n").alias("size"))
    ys = labels.select("y").distinct()
    grid = part_list(assigned, m).join(F.broadcast(ys))  # clients x classes
    out = grid.join(counts, ["part", "y"], "left").join(sizes, "part", "left")
    return out.select("part", "y", (F.lit(1.0) - F.coalesce("n", F.lit(0)) / (F.coalesce("size", F.lit(0)) + F.lit(EPSILON))).alias("label_div"))


def place(both: DataFrame, v: DataFrame, assigned: DataFrame, labels: DataFrame | None, cfg: Config) -> DataFrame:
    """Stage one: (vid, part) for the vertices of v that the primary objective can place, against a frozen assignment."""
    vol = volumes(both, assigned, cfg.clients)
    cast = votes(both, v, assigned)
    if cfg.primary == "cut":
        scored = cast.withColumn("score", F.col("votes").cast("double"))
    elif cfg.primary == "balance":
        return levelled(both, v, vol, cfg.clients)
    else:
        div = label_diversity(assigned, labels, cfg.clients)
        with_y = v.select("vid").join(labels, "vid")
        scored = with_y.join(F.broadcast(div), "y").withColumn("score", F.col("label_div"))
        plain = cast.join(with_y, "vid", "left_anti").withColumn("score", F.col("votes").cast("double"))
        scored = scored.select("vid", "part", "score").unionAll(plain.select("vid", "part", "score"))
    best = scored.join(F.broadcast(vol), "part").groupBy("vid").agg(F.max_by("part", F.struct("score", -F.col("vol"), -F.col("part"))).alias("part"))
    return best.select("vid", "part")


def levelled(both: DataFrame, v: DataFrame, vol: DataFrame, m: int, buckets: int = 1024) -> DataFrame:
    """(vid, part): vertices, each as heavy as its edge ends (one at least), poured into the lightest clients.

    All clients below a common level are filled up to it, lightest first. Vertices get their place on the line of
    cumulative weight in two levels (``buckets`` of ids, then within each), and the place says which client's stretch of
    the line it falls into; the line is cut into as many pieces as clients, so that this join is one by equality.
    """
    deg = both.join(v.select(F.col("vid").alias("src")).distinct(), "src", "left_semi").groupBy(F.col("src").alias("vid")).agg(F.count(F.lit(1)).alias("deg"))
    heavy = v.select("vid").distinct().join(deg, "vid", "left").select("vid", F.greatest(F.coalesce("deg", F.lit(1)), F.lit(1)).cast("long").alias("w"), F.pmod("vid", F.lit(buckets)).alias("bucket"))
    heavy = materialise(heavy, "weights")
    sums = heavy.groupBy("bucket").agg(F.sum("w").alias("s"))
    offsets = sums.select("bucket", (F.sum("s").over(Window.orderBy("bucket")) - F.col("s")).alias("before"))  # one row a bucket
    within = F.sum("w").over(Window.partitionBy("bucket").orderBy("vid")) - F.col("w")
    line = heavy.withColumn("at", within).join(F.broadcast(offsets), "bucket").select("vid", (F.col("at") + F.col("before")).alias("at"))
    total = heavy.agg(F.coalesce(F.sum("w"), F.lit(0)).alias("t")).first()["t"]
    order = Window.orderBy("vol", "part")  # clients only, here and below
    ranked = vol.withColumn("j", F.row_number().over(order).cast("long")).withColumn("upto", F.sum("vol").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    used = materialise(ranked.filter(F.col("j") * F.col("vol") - F.col("upto") < total), "levels")
    top = used.agg(F.max("j").alias("k"), F.max_by("upto", "j").alias("u")).first()
    if top["k"] is None:
        return v.select("vid", F.lit(0).alias("part")).limit(0)
    # the level is (total + u) / k; a client's stretch ends where j times the level exceeds the volume so far
    end = F.ceil((F.col("j") * F.lit(total + top["u"]) - F.lit(top["k"]) * F.col("upto")) / F.lit(top["k"]))
    used = used.select("part", end.cast("long").alias("hi"), F.coalesce(F.lag(end).over(Window.orderBy("j")), F.lit(0)).cast("long").alias("lo"))
    piece = -(-total // m)
    pieces = used.filter("lo < hi").withColumn("piece", F.explode(F.sequence(F.floor(F.col("lo") / piece), F.floor((F.col("hi") - 1) / piece))))
    dealt = line.withColumn("piece", F.floor(F.col("at") / piece)).join(pieces, "piece").filter("at >= lo and at < hi")
    return dealt.select("vid", "part")


def lightest(both: DataFrame, v: DataFrame, assigned: DataFrame, m: int) -> DataFrame:
    """(vid, part): everything into the client with the least edge volume."""
    part = volumes(both, assigned, m).agg(F.min_by("part", F.struct("vol", "part")).alias("part"))
    return v.select("vid").join(F.broadcast(part)).select("vid", "part")


def refine_scores(both: DataFrame, v: DataFrame, assigned: DataFrame, labels: DataFrame | None, cfg: Config) -> DataFrame:
    """(vid, part, votes, score, now): stage-two score of each candidate client and of the present one.

    Candidates are the clients of real neighbours. The balance of a client without a neighbour of the vertex is 0.
    """
    current = assigned.join(v.select("vid").distinct(), "vid", "left_semi").select("vid", F.col("part").alias("now"))
    cast = votes(both, v, assigned)
    deg = cast.groupBy("vid").agg(F.sum("votes").alias("deg"))
    cand = cast.select("vid", "part").unionAll(current.select("vid", F.col("now").alias("part"))).distinct()
    cand = cand.join(cast, ["vid", "part"], "left").join(deg, "vid", "left").join(current, "vid").fillna(0, ["votes", "deg"])
    cand = cand.join(F.broadcast(balance(volumes(both, assigned, cfg.clients))), "part")
    cand = cand.withColumn("balance", F.when(F.col("votes") > 0, F.col("balance")).otherwise(0.0))
    if labels is not None:
        div = label_diversity(assigned, labels, cfg.clients)
        cand = cand.join(labels, "vid", "left").join(F.broadcast(div), ["part", "y"], "left").withColumn("label_div", F.coalesce("label_div", F.lit(1.0)))
    else:
        cand = cand.withColumn("label_div", F.lit(1.0))
    cutshare = F.when(F.col("deg") > 0, F.col("votes") / F.col("deg")).otherwise(0.0)
    first, second = {"cut": (F.col("balance"), F.col("label_div")), "balance": (cutshare, F.col("label_div")), "label": (cutshare, F.col("balance"))}[cfg.primary]
    score: Column = F.round(cfg.alpha * first + (1 - cfg.alpha) * second, 9)
    return cand.select("vid", "part", "votes", score.alias("score"), "now")


def refine_moves(scored: DataFrame, n: int, cfg: Config) -> DataFrame:
    """(vid, part, gain): best allowed move of each vertex, at most ``cap`` of the mean client size into each client."""
    here = scored.filter("part = now").select("vid", F.col("score").alias("s0"), F.col("votes").alias("v0"))
    gains = scored.filter("part <> now").join(here, "vid").select("vid", "part", F.round(F.col("score") - F.col("s0"), 9).alias("gain"), (F.col("v0") - F.col("votes")).alias("lost"))
    allowed = gains.filter((F.col("gain") > cfg.tau) & (F.col("lost") <= cfg.max_new_cut))
    best = allowed.groupBy("vid").agg(F.max_by(F.struct("part", "gain"), F.struct("gain", -F.col("part"))).alias("m")).select("vid", "m.part", "m.gain")
    cap = max(1, math.ceil(cfg.cap * n / cfg.clients))
    order = Window.partitionBy("part").orderBy(F.desc("gain"), "vid")
    return best.withColumn("nth", F.row_number().over(order)).filter(F.col("nth") <= cap).select("vid", "part", "gain")


def refine(both: DataFrame, v: DataFrame, assigned: DataFrame, labels: DataFrame | None, cfg: Config) -> DataFrame:
    """Stage two: rounds of moves, vertices of even and odd key in turn so that neighbours do not swap past each other."""
    n = assigned.count()
    for r in range(cfg.rounds):
        turn = v.filter(F.pmod(key_of("vid"), F.lit(2)) == r % 2)
        moves = materialise(refine_moves(refine_scores(both, turn, assigned, labels, cfg), n, cfg), "moves")
        if moves.isEmpty():
            if r:
                break
            continue
        assigned = materialise(assigned.join(moves.select("vid", F.col("part").alias("to")), "vid", "left").select("vid", F.coalesce("to", "part").alias("part")), "assignment")
    return assigned


# --- whole procedures


def initial(e: DataFrame, labels: DataFrame | None = None, cfg: Config | None = None) -> DataFrame:
    """(vid, part) from scratch: stitch, distant seeds, level-by-level growth with conflicts settled by stage one, stage two."""
    cfg = cfg or Config()
    e = materialise(e.select("a", "b"), "real")
    real = materialise(symmetric(e.withColumn("first", F.lit(0))).select("src", "dst"), "both")
    extra = stitch(e, components(e))
    joined = materialise(e.unionAll(extra), "stitched")
    steer = materialise(symmetric(joined.withColumn("first", F.lit(0))).select("src", "dst"), "steer")
    every = materialise(vertices(e), "vertices")
    seeds = far_seeds(joined, cfg.clients)
    spark = e.sparkSession
    rows = ", ".join(f"({v}L, {i})" for i, v in enumerate(seeds))
    if not rows:
        return every.select("vid", F.lit(0).alias("part"))
    assigned = spark.sql(f"select * from values {rows} as t(vid, part)")
    disputed = every.limit(0)
    last = assigned  # a vertex next to an earlier level has been reached by now
    for _ in range(cfg.max_level):
        near = materialise(reached(steer, last, every.join(assigned, "vid", "left_anti")), "reached")
        if near.isEmpty():
            break
        last, tied = near.filter("owners = 1").select("vid", "part"), near.filter("owners > 1").select("vid")
        if not tied.isEmpty():
            disputed = disputed.unionAll(tied)
            base = assigned.unionByName(last)
            settled = materialise(place(real, tied, base, labels, cfg), "settled")
            left = tied.join(settled, "vid", "left_anti")
            last = materialise(last.unionByName(settled).unionByName(lightest(real, left, base, cfg.clients)), "placed")
        assigned = materialise(assigned.unionByName(last), "assignment")
    rest = every.join(assigned, "vid", "left_anti")
    assigned = materialise(assigned.unionByName(lightest(real, rest, assigned, cfg.clients)), "assignment")
    scope = disputed
    if cfg.scope == "border":
        pairs = real.join(assigned.withColumnRenamed("vid", "src"), "src").join(assigned.select(F.col("vid").alias("dst"), F.col("part").alias("p2")), "dst")
        scope = scope.unionAll(pairs.filter("part <> p2").select(F.col("src").alias("vid"))).distinct()
    return refine(real, materialise(scope, "scope"), assigned, labels, cfg)


def extend(prev: DataFrame, e: DataFrame, labels: DataFrame | None = None, cfg: Config | None = None) -> DataFrame:
    """The next assignment: departed vertices go, old ones stay, new ones are placed by votes over one hop, then two.

    What still has no vote goes to the lightest client; stage two then moves new vertices only.
    """
    cfg = cfg or Config()
    both = symmetric(e.select("a", "b", F.lit(0).alias("first"))).select("src", "dst")
    every = vertices(e)
    kept = materialise(prev.join(every, "vid", "left_semi").select("vid", "part"), "kept")
    new = materialise(every.join(kept, "vid", "left_anti"), "new")
    one = materialise(place(both, new, kept, labels, cfg), "placed")
    left = new.join(one, "vid", "left_anti")
    two = materialise(place(two_hop(both, left), left, kept.unionByName(one), labels, cfg), "placed")
    base = kept.unionByName(one).unionByName(two)
    rest = new.join(base, "vid", "left_anti")
    placed = materialise(base.unionByName(lightest(both, rest, base, cfg.clients)), "assignment")
    return refine(both, new, placed, labels, cfg)


def two_hop(both: DataFrame, v: DataFrame) -> DataFrame:
    """(src, dst): distinct two-step neighbours of the vertices of v; only their own edges are expanded."""
    near = both.join(v.select(F.col("vid").alias("src")).distinct(), "src", "left_semi")
    return near.join(both.select(F.col("src").alias("dst"), F.col("dst").alias("far")), "dst").filter("src <> far").select("src", F.col("far").alias("dst")).distinct()


def advance(prev: DataFrame | None, e: DataFrame, labels: DataFrame | None = None, cfg: Config | None = None, was: int | None = None) -> DataFrame:
    """One snapshot on: extend a partition made for the same number of clients (``was``), else start anew."""
    cfg = cfg or Config()
    return extend(prev, e, labels, cfg) if is_valid(prev, was, cfg.clients) else initial(e, labels, cfg)


def run(edges: DataFrame, last: int, labels: DataFrame | None = None, cfg: Config | None = None, full: bool = False) -> DataFrame:
    """(snap, vid, part, clients) over snapshots 0..last; ``full`` partitions each from scratch. A loop over snapshots, one
    plan each; the number of clients is taken anew for each snapshot, and a change of it starts anew."""
    from .snapshots import at

    cfg = cfg or Config()
    prev, out, was = None, None, None
    for t in range(last + 1):
        now = at(edges, t)
        cfg = sized(now, cfg)
        prev = initial(now, labels, cfg) if full else advance(prev, now, labels, cfg, was)
        prev = materialise(prev.select("vid", "part"), "assignment")
        was = cfg.clients
        row = prev.select(F.lit(t).alias("snap"), "vid", "part", F.lit(was).alias("clients"))
        out = row if out is None else out.unionAll(row)
    return out
