"""What the coordinator does with client models: averaging, neighbour averaging, prototypes."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def average(params: DataFrame, weights: DataFrame | None = None) -> DataFrame:
    """(name, idx, value) from client rows (client, name, data array): weighted by (client, weight), else uniform."""
    flat = params.select("client", "name", F.posexplode("data").alias("idx", "val"))
    if weights is None:
        flat = flat.withColumn("weight", F.lit(1.0))
    else:
        flat = flat.join(F.broadcast(weights.filter("weight > 0")), "client")
    return flat.groupBy("name", "idx").agg((F.sum(F.col("val") * F.col("weight")) / F.sum("weight")).alias("value"))


def prototypes(h: DataFrame, labels: DataFrame) -> DataFrame:
    """(y, dim, value): mean vector of each class."""
    return h.join(labels, "vid").select("y", F.posexplode("x").alias("dim", "val")).groupBy("y", "dim").agg(F.avg("val").alias("value"))


def mean_models(models: list[dict[str, np.ndarray]], weights: list[float]) -> dict[str, np.ndarray]:
    """Weighted mean of client models held by the coordinator (a few kilobytes each)."""
    total = sum(weights) or 1.0
    return {k: sum(w * m[k] for m, w in zip(models, weights, strict=True)) / total for k in models[0]}


def ring(models: list[dict[str, np.ndarray]]) -> list[dict[str, np.ndarray]]:
    """Decentralised averaging: each client with its two neighbours on a ring."""
    n = len(models)
    return [{k: (models[i - 1][k] + models[i][k] + models[(i + 1) % n][k]) / 3 for k in models[i]} for i in range(n)]
