"""Message passing: aggregation over neighbours and the vertex itself, then a dense layer."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import plus, summed, width

ACTIVATIONS = {"identity": lambda z: z, "relu": lambda z: np.maximum(z, 0), "tanh": np.tanh}


def aggregate(both: DataFrame, h: DataFrame, how: str = "sum", targets: DataFrame | None = None, d: int | None = None) -> DataFrame:
    """(vid, x): sum or mean of the vectors of each vertex and its neighbours.

    ``both`` holds each edge in both directions (src, dst), ``h`` the vectors (vid, x). ``targets`` restricts what is
    computed, by a semi-join below the aggregation; a vertex without an edge keeps its own vector.
    """
    d = d or width(h)
    if targets is not None:
        both = both.join(targets.select(F.col("vid").alias("src")).distinct(), "src", "left_semi")
        own = h.join(targets.select("vid").distinct(), "vid", "left_semi")
    else:
        own = h
    sent = both.select("src", "dst").join(h.select(F.col("vid").alias("dst"), "x"), "dst").select(F.col("src").alias("vid"), "x")
    every = own.select("vid", "x").unionAll(sent)
    if how == "sum":
        return summed(every, "vid", d)
    if how == "mean":
        from ..functions.vectors import averaged

        return averaged(every, "vid", d)
    if how == "sym":
        degree = both.groupBy(F.col("src").alias("vid")).agg((F.count(F.lit(1)) + 1).alias("deg"))
        scaled = h.join(degree, "vid", "left").select("vid", F.transform("x", lambda v: v / F.sqrt(F.coalesce("deg", F.lit(1)))).alias("x"))
        out = aggregate(both, scaled, "sum", targets, d)
        return out.join(degree, "vid", "left").select("vid", F.transform("x", lambda v: v / F.sqrt(F.coalesce("deg", F.lit(1)))).alias("x"))
    raise ValueError(f"unknown aggregation {how!r}")


def dense_sql(z: DataFrame, weight: list[list[float]], act: str = "relu") -> DataFrame:
    """(vid, x) times a small matrix (rows: inputs), in expressions only; for d of a few."""
    columns = []
    for j in range(len(weight[0])):
        s = F.lit(0.0)
        for i in range(len(weight)):
            s = s + F.get("x", F.lit(i)) * F.lit(float(weight[i][j]))
        columns.append({"identity": s, "relu": F.greatest(s, F.lit(0.0)), "tanh": F.tanh(s)}[act])
    return z.select("vid", F.array(*columns).alias("x"))


def matrix(column: pa.Array) -> np.ndarray:
    """Rows of equal length as one matrix, without a Python object a row."""
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1) if len(column) else flat.reshape(0, 0)


def vectors(rows: np.ndarray) -> pa.Array:
    n, d = rows.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(0, n * d + 1, d or 1, dtype=np.int32)[: n + 1]), pa.array(rows.ravel()))


def dense(z: DataFrame, weight: np.ndarray, act: str = "relu") -> DataFrame:
    """(vid, x) times a matrix, a batch at a time."""
    f = ACTIVATIONS[act]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column("vid"), vectors(f(matrix(b.column("x")) @ weight))], names=["vid", "x"])

    return z.select("vid", F.col("x").cast("array<double>").alias("x")).mapInArrow(work, "vid long, x array<double>")


def with_own(h: DataFrame, added: DataFrame) -> DataFrame:
    """h + added where there is a row to add; others unchanged."""
    return h.join(added.select("vid", F.col("x").alias("_a")), "vid", "left").select("vid", F.when(F.col("_a").isNull(), F.col("x")).otherwise(plus("x", "_a")).alias("x"))
