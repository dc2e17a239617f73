"""Session defaults for programs that start their own; queries work with any session as given."""

from __future__ import annotations

from pyspark.sql import SparkSession


def session(app: str = "dyngraph", master: str | None = None, **conf: str) -> SparkSession:
    """UTC, adaptive execution with skew handling; further settings by keyword with dots as double underscores."""
    builder = SparkSession.builder.appName(app)
    if master:
        builder = builder.master(master)
    settings = {
        "spark.sql.session.timeZone": "UTC",
        "spark.sql.adaptive.enabled": "true",
        "spark.sql.adaptive.skewJoin.enabled": "true",
        "spark.sql.execution.arrow.pyspark.enabled": "true",
        "spark.ui.enabled": "false",
    } | {k.replace("__", "."): v for k, v in conf.items()}
    return builder.config(map=settings).getOrCreate()
