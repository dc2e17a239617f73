"""Incremental training: stacked layers with a recurrent update over the region, local steps in one task a client.

The forward pass over the whole region is a Spark plan (``forward``). Client training holds one client's subgraph in
one task, whose size the number of clients bounds, and runs all its epochs there, so a round is one job.
"""

from __future__ import annotations

import threading
from collections.abc import Callable
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import width
from ..sources.graphs import symmetric, vertices
from ..sources.tables import materialise
from . import clients, exchange, federate, message, recurrent, region
from .snapshots import at

Model = dict[str, np.ndarray]


class Held(dict):
    """Tables that several runs share, with a lock, since runs may be threads."""

    def __init__(self) -> None:
        super().__init__()
        self.lock = threading.Lock()


def once(held: Held | None, key: tuple, make: Callable[[], DataFrame]) -> DataFrame:
    if held is None:
        return make()
    with held.lock:
        if key not in held:
            held[key] = make()
        return held[key]


@dataclass(frozen=True)
class Settings:
    """``mode``: incremental or full. ``scheme``: how remote neighbours count (none, feature_sum, exchange). ``hops``: 1
    corrects the first layer's sums; 2 trains on two-hop sums with their complete correction, which are exact.
    ``cell``: the last layer passes through a gated recurrent cell with the state of the snapshot before, or not."""

    task: str = "link"
    hidden: int = 8
    layers: int = 2
    hops: int = 1
    rounds: int = 3
    epochs: int = 3
    rate: float = 0.1
    seed: int = 1
    mode: str = "incremental"
    scheme: str = "exchange"
    schedule: exchange.Schedule = exchange.Schedule()
    cell: str = "gru"
    aggregate: str = "mean"
    evolve: str = ""  # weights evolve by a recurrent cell instead of states: "h" (input-driven) or "o"
    averaging: str = "weighted"  # weighted, ring, prototypes
    replay: float = 0.0
    importance: float = 0.0
    influence: bool = False
    generate: bool = False


def model(d: int, classes: int, s: Settings) -> Model:
    rng = np.random.default_rng(s.seed)
    sizes = [d] + [s.hidden] * s.layers
    out = {f"w{i}": rng.normal(scale=sizes[i] ** -0.5, size=(sizes[i], sizes[i + 1])) for i in range(s.layers)}
    out |= {"out": rng.normal(scale=s.hidden**-0.5, size=(s.hidden, classes))}
    out |= {f"g_{k}": v for k, v in recurrent.weights(s.hidden, s.seed).items()} if s.cell == "gru" else {}
    return out | ({f"i_{k}": np.zeros_like(v) for k, v in out.items()} if s.importance else {})


def gates_of(m: Model) -> dict[str, np.ndarray] | None:
    """The gates of the last layer's cell, if the model has one."""
    return {k[2:]: v for k, v in m.items() if k.startswith("g_")} or None


def importances(grad: Model) -> Model:
    """How much the loss hangs on each parameter: squared gradients, scaled to a mean of one over the whole model."""
    squares = {k: v**2 for k, v in grad.items() if not k.startswith("i_")}
    mean = sum(v.sum() for v in squares.values()) / sum(v.size for v in squares.values())
    return {f"i_{k}": v / mean if mean else np.zeros_like(v) for k, v in squares.items()}


def forward(edges: DataFrame, feats: DataFrame, weights: list[np.ndarray], how: str = "sum", rings: DataFrame | None = None, before: list[DataFrame] | None = None, gates: list[dict] | None = None, act: str = "relu", recurrent_input: str = "hidden", last_act: str | None = None) -> list[DataFrame]:
    """States (vid, x) after each layer. With ``rings`` (layer, vid) only those are computed and ``before`` fills the rest.

    ``gates`` fuse a layer with its states in ``before`` (zero where there are none); None leaves the layer as it is.
    ``how='own'`` takes ``feats`` for sums already. ``recurrent_input='raw'`` feeds the next layer the plain output.
    """
    both = symmetric(edges.select("a", "b", F.lit(0).alias("first")))
    h, out = feats.select("vid", F.col("x").cast("array<double>").alias("x")), []
    for layer, w in enumerate(weights, 1):
        todo = rings.filter(F.col("layer") == layer).select("vid") if rings is not None else None
        if how == "own":
            summed = h.join(todo.select("vid").distinct(), "vid", "left_semi") if todo is not None else h
        else:
            summed = message.aggregate(both, h, how, todo, d=w.shape[0])
        raw = message.dense(summed, w, act if layer < len(weights) else last_act or act)
        prev = before[layer - 1] if before else None
        gate = gates[layer - 1] if gates else None
        new = recurrent.gru(raw, prev if prev is not None else raw.limit(0), gate) if gate else raw
        new = materialise(new, "layer")
        full = materialise(recurrent.assemble(new, prev), "state") if prev is not None and todo is not None else new
        out.append(full)
        h = full if recurrent_input == "hidden" or todo is None else recurrent.assemble(raw, prev)
    return out


# --- one client's step, in numpy


def add_at(out: np.ndarray, rows: np.ndarray, x: np.ndarray) -> None:
    """``np.add.at`` for matrices, a column at a time, which is many times faster; sums are taken in the same order."""
    where = np.concatenate([np.arange(len(out)), rows])
    for j in range(out.shape[1]):
        out[:, j] = np.bincount(where, np.concatenate([out[:, j], x[:, j]]), len(out))


def _adjacency(n: int, src: np.ndarray, dst: np.ndarray, how: str) -> Callable[[np.ndarray], np.ndarray]:
    """Multiplication by the normalised adjacency with self-loops, without forming it; ``own``: by the identity."""
    if how == "own":

        def same(x: np.ndarray) -> np.ndarray:
            return x

        same.back = same
        return same
    deg = 1.0 + np.bincount(src, minlength=n)

    def mul(x: np.ndarray) -> np.ndarray:
        out = x.copy()
        add_at(out, src, x[dst])
        return out / deg[:, None] if how == "mean" else out

    def back(g: np.ndarray) -> np.ndarray:
        g = g / deg[:, None] if how == "mean" else g
        out = g.copy()
        add_at(out, dst, g[src])
        return out

    mul.back = back
    return mul


def loss_and_gradient(m: Model, x: np.ndarray, mul, task: str, y: np.ndarray, pairs: np.ndarray | None, extra: np.ndarray | None = None, prev: np.ndarray | None = None) -> tuple[float, Model]:
    """Mean loss and its gradient by hand: softmax cross-entropy over labelled rows (y >= 0), or logistic over pairs (u, v, y).

    ``extra`` is added to the first layer's aggregate: what other clients' vertices would have sent. Where the model has
    gates, the last layer is fused with the previous states ``prev`` (zero if not given), which are constants here.
    """
    gates = gates_of(m)
    layers = len([k for k in m if k.startswith("w")])
    zs, hs = [], [x]
    for i in range(layers):
        z = mul(hs[-1])
        if i == 0 and extra is not None:
            z = z + extra
        zs.append(z)
        hs.append(np.maximum(z @ m[f"w{i}"], 0.0) if i < layers - 1 else z @ m[f"w{i}"])
    raw, grad = hs[-1], {k: np.zeros_like(v) for k, v in m.items()}
    prev = np.zeros_like(raw) if prev is None else prev
    h = recurrent.step(raw, prev, gates) if gates else raw
    if task == "class":
        rows = np.flatnonzero(y >= 0)
        if not len(rows):
            return 0.0, grad
        s = h[rows] @ m["out"]
        s -= s.max(axis=1, keepdims=True)
        p = np.exp(s)
        p /= p.sum(axis=1, keepdims=True)
        loss = float(-np.log(p[np.arange(len(rows)), y[rows]] + 1e-12).mean())
        p[np.arange(len(rows)), y[rows]] -= 1
        p /= len(rows)
        grad["out"] = h[rows].T @ p
        gh = np.zeros_like(h)
        gh[rows] = p @ m["out"].T
    else:
        if pairs is None or not len(pairs):
            return 0.0, grad
        u, v, t = pairs[:, 0], pairs[:, 1], pairs[:, 2]
        s = (h[u] * h[v]).sum(axis=1)
        p = 1 / (1 + np.exp(-np.clip(s, -50, 50)))
        loss = float(-(t * np.log(p + 1e-12) + (1 - t) * np.log(1 - p + 1e-12)).mean())
        e = ((p - t) / len(pairs))[:, None]
        gh = np.zeros_like(h)
        add_at(gh, u, e * h[v])
        add_at(gh, v, e * h[u])
    if gates:
        gh, by_gate = recurrent.step_gradient(raw, prev, gates, gh)
        grad |= {f"g_{k}": v for k, v in by_gate.items()}
    for i in range(layers - 1, -1, -1):
        if i < layers - 1:
            gh = gh * (hs[i + 1] > 0)
        grad[f"w{i}"] = zs[i].T @ gh
        gh = mul.back(gh @ m[f"w{i}"].T)
    return loss, grad


def _pairs(src: np.ndarray, dst: np.ndarray, n: int, rng: np.random.Generator) -> np.ndarray:
    """Each edge once, and as many random pairs that are none."""
    one = src < dst
    u, v = src[one], dst[one]
    if not len(u) or n < 3:
        return np.empty((0, 3), np.int64)
    a, b = rng.integers(0, n, 4 * len(u)), rng.integers(0, n, 4 * len(u))
    ok = (a != b) & ~np.isin(a * n + b, src * n + dst)
    a, b = a[ok][: len(u)], b[ok][: len(u)]
    return np.concatenate([np.c_[u, v, np.ones_like(u)], np.c_[a, b, np.zeros_like(a)]])


def local_step(nodes: pd.DataFrame, pairs: pd.DataFrame, m: Model, anchor: Model, s: Settings, received: list[bool] | None = None) -> pd.DataFrame:
    """All epochs of one client; returns its model as rows (part, weight, loss, name, data).

    ``received`` says for each epoch whether corrections have reached the client by then. With ``importance`` each
    parameter is drawn to the snapshot before (``anchor``) by the weight it had there, and new weights are returned.
    """
    part = int(nodes["part"].iloc[0]) if len(nodes) else int(pairs["part"].iloc[0])
    rows = lambda w, loss, mm: pd.DataFrame({"part": part, "weight": float(w), "loss": float(loss), "name": list(mm), "data": [v.ravel().tolist() for v in mm.values()]})
    if not len(nodes):
        return rows(0, 0.0, m)
    nodes = nodes.sort_values("vid")
    ids, ends = nodes["vid"].to_numpy(np.int64), pairs[["src", "dst"]].to_numpy(np.int64)
    found = np.searchsorted(ids, ends).clip(max=len(ids) - 1)
    src, dst = found[(ids[found] == ends).all(axis=1)].T
    x = np.stack(nodes["x"].to_numpy()).astype(np.float64)
    extra = np.stack(nodes["extra"].to_numpy()).astype(np.float64)
    if s.generate:  # missing neighbours stand in with the client's mean feature
        extra = extra + x.mean(axis=0)
    prev = np.stack(nodes["prev"].to_numpy()).astype(np.float64)
    mul = _adjacency(len(nodes), src, dst, "own" if s.hops == 2 else s.aggregate)
    if s.aggregate == "mean" and s.hops == 1:
        extra = extra / (1.0 + np.bincount(src, minlength=len(nodes)))[:, None]
    y = np.where(nodes["train"].to_numpy(bool), nodes["y"].fillna(-1).to_numpy(np.int64), -1)
    rng = np.random.default_rng(s.seed + part)
    told = _pairs(src, dst, len(nodes), rng) if s.task == "link" else None
    m = {k: v.copy() for k, v in m.items()}
    loss = 0.0
    none = np.zeros_like(extra)
    for e in range(s.epochs):
        loss, g = loss_and_gradient(m, x, mul, s.task, y, told, extra if received is None or received[e] else none, prev)
        for k in [k for k in m if not k.startswith("i_")]:
            step = g[k] + (s.importance * anchor[f"i_{k}"] * (m[k] - anchor[k]) if s.importance else 0.0)
            size = float(np.sqrt((step**2).sum()))
            m[k] -= s.rate * step / max(1.0, size)
    if s.importance:
        m |= importances(loss_and_gradient(m, x, mul, s.task, y, told, extra if received is None or received[-1] else none, prev)[1])
    return rows(len(nodes), loss, m)


def _stepper(held, ring: bool, s: Settings, received: list[bool]) -> Callable[[pd.DataFrame, pd.DataFrame], pd.DataFrame]:
    """The function of one round: models come from the broadcast ``held``."""

    def work(nodes: pd.DataFrame, pairs: pd.DataFrame) -> pd.DataFrame:
        m, anchor, own = held.value
        if ring and own and len(nodes):
            m = own[int(nodes["part"].iloc[0]) % len(own)]
        return local_step(nodes, pairs, m, anchor, s, received)

    return work


def _unpack(rows: list, shapes: dict[str, tuple]) -> tuple[list[Model], list[float], list[float]]:
    by: dict[int, Model] = {}
    weight, loss = {}, {}
    for r in rows:
        by.setdefault(r["part"], {})[r["name"]] = np.array(r["data"]).reshape(shapes[r["name"]])
        weight[r["part"]], loss[r["part"]] = r["weight"], r["loss"]
    parts = sorted(by)
    return [by[p] for p in parts], [weight[p] for p in parts], [loss[p] for p in parts]


def normalised(feats: DataFrame, d: int) -> DataFrame:
    """Features scaled to mean 0 and deviation 1 by one aggregation."""
    stats = feats.agg(*[F.avg(F.get("x", F.lit(i))).alias(f"m{i}") for i in range(d)], *[F.stddev_pop(F.get("x", F.lit(i))).alias(f"s{i}") for i in range(d)]).first()
    return feats.select("vid", F.array(*[(F.get("x", F.lit(i)) - F.lit(float(stats[f"m{i}"] or 0))) / F.lit(float(stats[f"s{i}"] or 1) or 1.0) for i in range(d)]).alias("x"))


def fit(edges: DataFrame, t: int, feats: DataFrame, labels: DataFrame | None, assigned: DataFrame, m: Model, s: Settings, d: int, before: DataFrame | None = None, held: Held | None = None) -> tuple[Model, list[dict]]:
    """Trains on snapshot t; returns the averaged model and a log with the loss of each round.

    Each client gets its vertices of the region, with features, labels, the last layer's states ``before`` and the
    corrections. These count from the epoch at which the schedule lets them arrive, and in all epochs and rounds after
    it: an exchange in a first epoch serves that epoch already, one after a last epoch serves the next round.
    """
    now = at(edges, t)
    every = vertices(now)
    reach = every.select("vid", F.lit(0).alias("hop")) if s.mode == "full" or t == 0 else once(held, ("reach", t, s.layers), lambda: region.chosen(edges, t, s.layers))
    if s.influence:  # only what lies next to a change
        reach = reach.filter("hop <= 1")
    if s.replay:
        old = every.filter(F.pmod(F.xxhash64("vid"), F.lit(1000)) < int(1000 * s.replay))
        reach = reach.select("vid", "hop").unionAll(old.select("vid", F.lit(0).alias("hop")))
    scope = materialise(reach.select("vid").distinct(), "scope")
    ee = materialise(clients.placed(now, assigned), "placed")
    zero = F.lit([0.0] * d)
    if s.scheme in ("none", "feature_sum"):
        extra = scope.select("vid", zero.alias("extra"))
        if s.scheme == "feature_sum":  # the sums take the place of the features
            feats = exchange.feature_sum(ee, feats, "owner", d)
    elif s.hops == 2:
        extra = exchange.hop2(ee, feats, "complete", scope, d).select("vid", F.col("x").alias("extra"))
    else:
        extra = exchange.hop1(ee, feats, scope, d).select("vid", F.col("x").alias("extra"))
    scale = 1.0
    if s.hops == 2:
        feats, scale = exchange.local_states(ee, feats, 2, d), two_hop_scale(now)
    states = (before if before is not None else scope.limit(0).withColumn("x", F.lit([0.0]))).select("vid", F.col("x").alias("prev"))
    still = F.lit([0.0] * s.hidden)
    scaled = lambda c: F.transform(c, lambda v: v * F.lit(scale))
    y = labels if labels is not None else every.select("vid", F.lit(-1).alias("y"))
    nodes = scope.join(assigned, "vid").join(feats, "vid").join(extra, "vid", "left").join(y, "vid", "left").join(states, "vid", "left")
    nodes = materialise(nodes.select("part", "vid", scaled("x").alias("x"), scaled(F.coalesce("extra", zero)).alias("extra"), F.coalesce("prev", still).alias("prev"), F.coalesce("y", F.lit(-1)).cast("long").alias("y"), (F.pmod(F.xxhash64("vid"), F.lit(10)) < 7).alias("train")), "nodes")
    pairs = materialise(clients.local(ee).join(scope.select(F.col("vid").alias("src")), "src", "left_semi").select(F.col("pu").alias("part"), "src", "dst"), "pairs")
    shapes = {k: v.shape for k, v in m.items()}
    spark, anchor, log = edges.sparkSession, m, []
    locals_: list[Model] | None = None
    arrived = s.scheme == "feature_sum"
    for r in range(1, s.rounds + 1):
        fires = [s.scheme == "exchange" and s.schedule.fires(e, r, s.epochs, s.rounds) for e in range(1, s.epochs + 1)]
        fired, received = any(fires), []
        for e in fires:
            arrived = arrived or (e and s.schedule.epoch == "first")
            received.append(arrived)
        arrived = arrived or fired
        held = spark.sparkContext.broadcast((m, anchor, locals_))
        ring = s.averaging == "ring"

        rows = nodes.groupBy("part").cogroup(pairs.groupBy("part")).applyInPandas(_stepper(held, ring, s, received), "part int, weight double, loss double, name string, data array<double>").collect()  # client models only
        models, weights, losses = _unpack(rows, shapes)
        if not models:
            break
        if ring:
            locals_ = federate.ring(models)
        m = federate.mean_models(models, weights if s.averaging != "uniform" else [1.0] * len(models))
        log.append({"round": r, "loss": float(np.average(losses, weights=np.maximum(weights, 1e-9))), "exchanged": fired, "clients": len(models)})
    return m, log


def embeddings(edges: DataFrame, t: int, feats: DataFrame, m: Model, s: Settings, before: list[DataFrame] | None, d: int, held: Held | None = None) -> list[DataFrame]:
    """States after every layer at snapshot t under the averaged model; incremental where ``before`` is given."""
    weights = [m[f"w{i}"] for i in range(s.layers)]
    rings = None
    if before is not None and s.mode == "incremental":
        rings = once(held, ("rings", t, s.layers), lambda: materialise(region.rings(at(edges, t), region.seeds(edges, t), s.layers), "rings"))
    gates = [None] * (s.layers - 1) + [gates_of(m)]
    now, how = at(edges, t), s.aggregate
    if s.hops == 2:  # the clients' corrected sums equal those over the whole graph
        both = symmetric(now.select("a", "b", F.lit(0).alias("first")))
        scale, how = two_hop_scale(now), "own"
        feats = exchange.truth(both, feats, 2, d).select("vid", F.transform("x", lambda v: v * F.lit(scale)).alias("x"))
    return forward(now, feats, weights, how, rings, before, gates, last_act="identity")


def two_hop_scale(now: DataFrame) -> float:
    """One over the square of the mean closed degree, by which two-hop sums are brought to the scale of features."""
    edges_, vertices_ = now.count(), vertices(now).count()
    return (1.0 + 2.0 * edges_ / max(1, vertices_)) ** -2


def evolved(m: Model, s: Settings, t: int) -> Model:
    """Weights moved on by a gated cell between snapshots, driven by themselves (``o``) or by their row means (``h``)."""
    out = dict(m)
    for i in range(s.layers):
        w = m[f"w{i}"].T  # one row an output, so that the cell mixes inputs
        cur = w if s.evolve == "o" else np.broadcast_to(w.mean(axis=0), w.shape)
        out[f"w{i}"] = recurrent.step(cur, w, recurrent.weights(w.shape[1], s.seed + 31 * t + i)).T
    return out


def live_update(edges: DataFrame, last: int, feats: DataFrame, labels: DataFrame | None, assigned: DataFrame, s: Settings, classes: int = 2, first: int = 0, held: Held | None = None) -> tuple[list[DataFrame], list[dict], Model]:
    """Trains on t, for t from ``first`` to ``last``, carrying model and states; returns last states, log and model.

    Runs on the same edges and features may share ``held``: what does not hang on the model is then made once.
    """
    d = width(feats)
    feats = once(held, ("features",), lambda: materialise(normalised(feats, d), "features"))
    m, before, log = model(d, classes, s), None, []
    for t in range(first, last + 1):
        if s.evolve and t > first:
            m = evolved(m, s, t)
        settings = s if t > first else replace(s, mode="full")
        m, rounds = fit(edges, t, feats, labels, assigned, m, settings, d, before[-1] if before else None, held)
        before = embeddings(edges, t, feats, m, settings, before, d, held)
        log += [{"snap": t, **x} for x in rounds]
    return before, log, m


def classify(h: DataFrame, m: Model) -> DataFrame:
    """(vid, yhat) from states and the output matrix."""
    out = m["out"]
    scored = message.dense(h, out, "identity")
    return scored.select("vid", F.array_position("x", F.array_max("x")).cast("long").alias("yhat")).withColumn("yhat", F.col("yhat") - 1)
