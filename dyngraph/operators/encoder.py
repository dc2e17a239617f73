"""A continuous-time pair encoder: recent neighbour sequences, co-occurrence counts, a small attention score."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def recent_neighbours(events: DataFrame, cut: str, recent: int) -> DataFrame:
    """(vid, near): the ``recent`` latest partners before ``cut``, newest first; both ends of each event count."""
    past = events.filter(F.col("ts") < F.lit(cut).cast("timestamp_ntz"))
    both = past.select(F.col("u").alias("vid"), F.col("v").alias("other"), "ts", "event_id").unionAll(past.select("v", "u", "ts", "event_id"))
    last = both.withColumn("n", F.row_number().over(Window.partitionBy("vid").orderBy(F.desc("ts"), F.desc("event_id")))).filter(F.col("n") <= recent)
    return last.groupBy("vid").agg(F.transform(F.array_sort(F.collect_list(F.struct("n", "other"))), lambda x: x["other"]).alias("near"))


def cooccurrence(near_u: str, near_v: str):
    """For each partner of u, how often it is among the partners of v."""
    return F.transform(near_u, lambda a: F.size(F.filter(near_v, lambda b: a == b)))


def pair_scores(pairs: DataFrame, near: DataFrame, recent: int, seed: int = 3) -> DataFrame:
    """(u, v, score): attention of v over u's sequence by co-occurrence and recency, through fixed small weights."""
    both = pairs.join(near.select(F.col("vid").alias("u"), F.col("near").alias("nu")), "u", "left").join(near.select(F.col("vid").alias("v"), F.col("near").alias("nv")), "v", "left")
    empty = F.expr("cast(array() as array<bigint>)")
    both = both.withColumn("nu", F.coalesce("nu", empty)).withColumn("nv", F.coalesce("nv", empty))
    both = both.select("u", "v", cooccurrence("nu", "nv").alias("cu"), F.transform("nu", lambda a: (a == F.col("v")).cast("int")).alias("hit"))
    w = np.random.default_rng(seed).normal(size=4) * 0.1 + np.array([1.0, 1.0, 0.5, 0.0])

    def work(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            x = np.zeros((len(b), recent, 2))
            for i, (c, h) in enumerate(zip(b["cu"], b["hit"], strict=True)):
                x[i, : len(c), 0], x[i, : len(h), 1] = c, h
            age = np.arange(recent) / recent
            logits = w[0] * x[..., 0] + w[1] * x[..., 1] - age
            att = np.exp(logits - logits.max(axis=1, keepdims=True))
            att /= att.sum(axis=1, keepdims=True)
            yield pd.DataFrame({"u": b["u"], "v": b["v"], "score": np.round((att * (w[2] * x[..., 0] + x[..., 1])).sum(axis=1) + w[3], 6)})

    return both.mapInPandas(work, "u long, v long, score double")


def scores(events: DataFrame, cut: str, recent: int) -> DataFrame:
    """(u, v, score) for the distinct pairs that meet after ``cut``."""
    later = events.filter(F.col("ts") >= F.lit(cut).cast("timestamp_ntz")).select("u", "v").distinct()
    return pair_scores(later, recent_neighbours(events, cut, recent), recent)
