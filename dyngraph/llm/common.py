"""What the operators of this subpackage share: table access, shared folders, word splitting."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: White space between words: space, tab, line feed, vertical tab, form feed, carriage return.
SPACE = r"[\x20\x09-\x0D]+"

_written: list[tuple[SparkSession, str]] = []


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """The named table, cut down to ``columns`` (all when none are given) so the scan reads no more."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def shared_dir(spark: SparkSession) -> str:
    """A folder that driver and executors share: spark.checkpoint.dir, or, where unset, a local one (tests)."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        root = spark.sparkContext._jsc.sc().getCheckpointDir()
        root = root.get() if root.isDefined() else None
    if not root:
        root = "file://" + tempfile.mkdtemp(prefix="dyngraph-shared-")
        spark.sparkContext.setCheckpointDir(root)
    return root


def scratch_path(spark: SparkSession, label: str) -> str:
    """A fresh path below the shared folder; removed when the driver's Python ends."""
    path = f"{shared_dir(spark).rstrip('/')}/{label}-{uuid.uuid4().hex}"
    _written.append((spark, path))
    return path


def remove(spark: SparkSession, path: str) -> None:
    """Delete ``path`` on whatever file system holds it."""
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


@atexit.register
def _tidy() -> None:
    for spark, path in _written:
        try:
            remove(spark, path)
        except Exception:  # the JVM may be gone already
            return


def written(df: DataFrame, label: str) -> DataFrame:
    """Cut lineage through a Parquet table in the shared folder, which outlives lost executors."""
    path = scratch_path(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def settled(condition: Column) -> Column:
    """The same truth value, but computed where it stands.

    A filter on a plain column is pushed below the projections that make it, and their array expressions would be
    evaluated anew within each lambda that refers to them; a non-deterministic column stops that.
    """
    return condition & (F.monotonically_increasing_id() >= 0)


def words(text: Column) -> Column:
    """Array of the maximal runs without white space; empty for null."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), SPACE), "")
