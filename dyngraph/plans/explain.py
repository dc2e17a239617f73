"""What a plan holds, for tests and for reading plans at scale."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def phases(df: DataFrame) -> dict[str, str]:
    """Text of the logical, analysed, optimised and physical plan."""
    q = df._jdf.queryExecution()
    return {"logical": q.logical().toString(), "analysed": q.analyzed().toString(), "optimised": q.optimizedPlan().toString(), "physical": q.executedPlan().toString()}


def operators(df: DataFrame) -> list[str]:
    """Names of the physical operators, top down."""
    return re.findall(r"(?m)^[\s:+\-*()\d]*([A-Z]\w+)", phases(df)["physical"])


def exchanges(df: DataFrame) -> int:
    return sum("Exchange" in x for x in operators(df))


def pushed(df: DataFrame) -> str:
    """Filters that reach the file scans."""
    return " ".join(re.findall(r"PushedFilters: \[[^\]]*\]", phases(df)["physical"]))
