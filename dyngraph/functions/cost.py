"""Cost measures: the closed communication model, what an outbox really holds, wall clock, counters."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F


def model(params: DataFrame) -> DataFrame:
    """name, bytes, seconds from rows of (name, firings, ratio, edges, dim, width, snaps, latency): two numbers, never added."""
    size = F.col("firings") * F.col("ratio") * F.col("edges") * F.col("dim") * F.col("width")
    return params.select("name", F.round(size, 3).alias("bytes"), F.round(F.col("snaps") * F.col("latency"), 6).alias("seconds"))


def actual(outbox: DataFrame, width: int = 4) -> DataFrame:
    """Messages and bytes by client and hop: an id of 8 bytes and the vector."""
    return outbox.groupBy("part", "hop").agg(F.count(F.lit(1)).alias("messages"), F.sum(8 + width * F.size("x")).cast("long").alias("bytes"))


def ratio(a: float, b: float) -> float:
    return a / b if b else float("inf")


@dataclass
class Stopwatch:
    """Seconds of named stages; ``timed`` runs a stage to a row count through a sink that stores nothing."""

    seconds: dict[str, float] = field(default_factory=dict)
    rows: dict[str, int] = field(default_factory=dict)

    def timed(self, name: str, make: Callable[[], DataFrame]) -> DataFrame:
        began = time.perf_counter()
        df = make()
        seen = Observation()
        df.observe(seen, F.count(F.lit(1)).alias("rows")).write.format("noop").mode("overwrite").save()
        self.seconds[name] = self.seconds.get(name, 0.0) + time.perf_counter() - began
        self.rows[name] = seen.get["rows"]
        return df


def counters(df: DataFrame, name: str) -> tuple[DataFrame, Observation]:
    """``df`` with an observation of its rows that is filled by whatever action runs it."""
    seen = Observation(name)
    return df.observe(seen, F.count(F.lit(1)).alias("rows")), seen
