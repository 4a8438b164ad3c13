"""Lineage cuts and size-checked broadcasts.

A written table lives under the folder that the cluster names in ``spark.checkpoint.dir``; executors may
be lost at any time and the rows are still there.  Only where the setting is absent (unit tests, a single
machine) a local folder is used instead.
"""

from __future__ import annotations

import atexit
import re
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

LOCAL_FALLBACK = "file:///tmp/checkpoints"

#: A side is broadcast up to this many rows; callers pass fewer for wide rows.
BROADCAST_ROWS = 200_000

_written: dict[str, SparkSession] = {}


def shared_folder(spark: SparkSession) -> str:
    """The folder every executor sees; without the setting only a master in this very process will do."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
        raise RuntimeError("spark.checkpoint.dir is not set: intermediate tables need a folder that all executors share")
    return (named or LOCAL_FALLBACK).rstrip("/")


def materialise(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` once to the shared folder and return a plan that reads it back."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/conflate-{label}-{uuid.uuid4().hex}"
    # zstd keeps its buffers on the heap; those of the default stand outside it until a collection
    df.write.option("compression", "zstd").parquet(path)
    _written[path] = spark
    back = spark.read.schema(df.schema).parquet(path)
    back._conflate_path = path
    return back


def discard(df: DataFrame) -> None:
    """Remove a materialised table that no later plan reads."""
    path = getattr(df, "_conflate_path", None)
    if path and path in _written:
        _remove(path, _written.pop(path))


def _remove(path: str, spark: SparkSession) -> None:
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


@atexit.register
def _clean() -> None:
    for path, spark in list(_written.items()):
        try:
            _remove(path, spark)
        except Exception:  # the session may already be gone; the folder is the cluster's to empty
            return


def broadcast_if_small(df: DataFrame, rows: int | None = None, limit: int = BROADCAST_ROWS) -> DataFrame:
    """Hint a broadcast only after counting; beyond ``limit`` rows the join shuffles instead."""
    n = df.count() if rows is None else rows
    return F.broadcast(df) if n <= limit else df
