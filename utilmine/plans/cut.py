"""Where plans are cut: caches within a loop, tables in the shared folder across it, and broadcasts of a checked size."""

from __future__ import annotations

import tempfile
import threading
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    """A new folder below spark.checkpoint.dir, the storage that the cluster shares, or the checkpoint folder set on the context. Without either, local
    sessions get a temporary folder; on a cluster that would lose rows and is an error."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        context = spark.sparkContext
        current = context._jsc.sc().getCheckpointDir()
        if current.isDefined():
            root = current.get()
        elif context.master.startswith("local") and not context.master.startswith("local-cluster"):
            root = tempfile.mkdtemp(prefix="spark-shared-")
            context.setCheckpointDir(root)
        else:
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return f"{root.rstrip('/')}/{uuid.uuid4().hex}"


def written(df: DataFrame) -> DataFrame:
    path = shared_folder(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


_held = threading.local()


def cached(df: DataFrame) -> DataFrame:
    if getattr(_held, "tables", None):
        _held.tables[-1].append(df)
    return df.persist(StorageLevel.MEMORY_AND_DISK)


@contextmanager
def released() -> Iterator[None]:
    """What is cached inside is dropped at its end. A session forgets no cached table by itself: a row of runs would fill memory and disk, and every plan
    is compared with all of them."""
    _held.tables = [*getattr(_held, "tables", []), []]
    try:
        yield
    finally:
        for df in _held.tables.pop():
            df.unpersist()


#: Rows of the largest table that is broadcast. Its rows are of bounded size: ranks, thresholds, sums and itemsets, never arrays that grow with the data.
MOST_ROWS = 200_000


def broadcast_if(df: DataFrame, rows: int, most: int = MOST_ROWS) -> DataFrame:
    """df with a broadcast hint if the known number of its rows is at most `most`."""
    return F.broadcast(df) if rows <= most else df


def broadcast_if_small(df: DataFrame, most: int = MOST_ROWS) -> DataFrame:
    """The same for a number of rows that a bounded count has to find."""
    return broadcast_if(df, df.limit(most + 1).count(), most)
