"""Temporal update of vertex states, and states as append-only versions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .message import matrix, vectors


def weights(d: int, seed: int = 0) -> dict[str, np.ndarray]:
    """Gate matrices for inputs (wz, wr, wh) and previous states (uz, ur, uh), and biases (bz, br, bh)."""
    rng = np.random.default_rng(seed)
    out = {f"{m}{g}": rng.normal(scale=d**-0.5, size=(d, d)) for g in "zrh" for m in "wu"}
    return out | {f"b{g}": np.zeros(d) for g in "zrh"}


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -60, 60)))


def step(cur: np.ndarray, prev: np.ndarray, w: dict[str, np.ndarray]) -> np.ndarray:
    """One gated recurrent step for a matrix of rows."""
    z = _sigmoid(cur @ w["wz"] + prev @ w["uz"] + w["bz"])
    r = _sigmoid(cur @ w["wr"] + prev @ w["ur"] + w["br"])
    h = np.tanh(cur @ w["wh"] + (r * prev) @ w["uh"] + w["bh"])
    return (1 - z) * prev + z * h


def step_gradient(cur: np.ndarray, prev: np.ndarray, w: dict[str, np.ndarray], out: np.ndarray) -> tuple[np.ndarray, dict[str, np.ndarray]]:
    """Gradients of ``step`` for the gradient ``out`` of its result: by the input, and by all gates. ``prev`` is given."""
    z = _sigmoid(cur @ w["wz"] + prev @ w["uz"] + w["bz"])
    r = _sigmoid(cur @ w["wr"] + prev @ w["ur"] + w["br"])
    h = np.tanh(cur @ w["wh"] + (r * prev) @ w["uh"] + w["bh"])
    by_h = out * z * (1 - h**2)
    by = {"z": out * (h - prev) * z * (1 - z), "r": (by_h @ w["uh"].T) * prev * r * (1 - r), "h": by_h}
    seen = {"z": prev, "r": prev, "h": r * prev}
    grad = {f"w{g}": cur.T @ e for g, e in by.items()} | {f"u{g}": seen[g].T @ e for g, e in by.items()} | {f"b{g}": e.sum(axis=0) for g, e in by.items()}
    return sum(e @ w[f"w{g}"].T for g, e in by.items()), grad


def gru(cur: DataFrame, prev: DataFrame, w: dict[str, np.ndarray]) -> DataFrame:
    """(vid, x): current layer output fused with the previous state; a missing state is zero."""
    d = len(w["bz"])
    zero = F.lit([0.0] * d)
    both = cur.select("vid", F.col("x").cast("array<double>").alias("x")).join(prev.select("vid", F.col("x").cast("array<double>").alias("p")), "vid", "left").withColumn("p", F.coalesce("p", zero))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column("vid"), vectors(step(matrix(b.column("x")), matrix(b.column("p")), w))], names=["vid", "x"])

    return both.mapInArrow(work, "vid long, x array<double>")


def gru_scalar(cur: DataFrame, prev: DataFrame, w: dict[str, float]) -> DataFrame:
    """The one-dimensional step in expressions (vid, x), for tests and oracles."""
    sig = lambda c: F.lit(1.0) / (F.lit(1.0) + F.exp(-c))
    both = cur.select("vid", F.col("x").cast("double").alias("x")).join(prev.select("vid", F.col("x").cast("double").alias("p")), "vid", "left").withColumn("p", F.coalesce("p", F.lit(0.0)))
    z = sig(F.col("x") * w["wz"] + F.col("p") * w["uz"])
    r = sig(F.col("x") * w["wr"] + F.col("p") * w["ur"])
    both = both.withColumn("z", z).withColumn("r", r)
    h = F.tanh(F.col("x") * w["wh"] + F.col("r") * F.col("p") * w["uh"])
    return both.select("vid", ((F.lit(1.0) - F.col("z")) * F.col("p") + F.col("z") * h).alias("x"))


def assemble(new: DataFrame, old: DataFrame) -> DataFrame:
    """Full state: the new rows, and the old ones of all other vertices."""
    return new.select("vid", "x").unionByName(old.join(new, "vid", "left_anti").select("vid", "x"))


def as_of(versions: DataFrame, t: int) -> DataFrame:
    """Latest state at or before t from appended versions (snap, vid, x)."""
    return versions.filter(F.col("snap") <= t).groupBy("vid").agg(F.max_by("x", "snap").alias("x"), F.max("snap").alias("snap"))


def compact(versions: DataFrame, t: int) -> DataFrame:
    """Versions with all that t has superseded left out."""
    return as_of(versions, t).select("snap", "vid", "x").unionByName(versions.filter(F.col("snap") > t).select("snap", "vid", "x"))
