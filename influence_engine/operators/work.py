"""Work tables in the cluster's shared folder, and broadcasts behind a counted bound."""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: A side is broadcast only when its counted rows stay below this bound.
BROADCAST_ROWS = 1_000_000


def shared_folder(spark: SparkSession, tag: str) -> str:
    """A fresh folder in the cluster's shared one; a local one only in local mode, where none is set."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local") or "cluster" in spark.sparkContext.master:
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        root = "file://" + os.path.join(tempfile.gettempdir(), "influence_engine_work")
    return f"{root.rstrip('/')}/{tag}-{uuid.uuid4().hex}"


def materialise(df: DataFrame, tag: str) -> DataFrame:
    """Written once and read back, so that nothing before it is computed again."""
    path = shared_folder(df.sparkSession, tag)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def bounded_broadcast(df: DataFrame, rows: int | None = None, limit: int = BROADCAST_ROWS) -> DataFrame:
    """Hint a broadcast when the counted rows stay within the limit, else leave it to a shuffle join."""
    n = df.count() if rows is None else rows
    return F.broadcast(df) if n <= limit else df


def together(spark: SparkSession, *builds: Callable[[], object]) -> list:
    """Results of builds that do not need each other; jobs of one run on cores that others leave idle."""
    with ThreadPoolExecutor(max(1, len(builds))) as pool:
        started = [pool.submit(inheritable_thread_target(spark)(build)) for build in builds]
        return [s.result() for s in started]


_written: dict[tuple, tuple[str, object]] = {}


def written(spark: SparkSession, key: tuple, build: Callable[[], DataFrame]) -> DataFrame:
    """A table that several queries of a session share: built and written when first asked for.

    Only its path is remembered; where the folder has been cleaned meanwhile, it is built anew.
    """
    own = (spark.sparkContext.applicationId, *key)
    if own in _written:
        path, schema = _written[own]
        place = spark._jvm.org.apache.hadoop.fs.Path(path)
        if place.getFileSystem(spark._jsc.hadoopConfiguration()).exists(place):
            return spark.read.schema(schema).parquet(path)
    df, path = build(), shared_folder(spark, str(key[-1]))
    df.write.parquet(path)
    _written[own] = (path, df.schema)
    return spark.read.schema(df.schema).parquet(path)
