"""Tables that cut lineage, in the folder that all executors share, and what Python workers keep between tasks."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Whether shuffle files are removed at the end of the execution that made them.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
#: Of this process: the caches made by worker_cache.
_CACHES: list = []


def worker_cache(maxsize: int) -> Callable:
    """lru_cache for what a Python worker keeps from one task to the next."""

    def wrap(f):
        _CACHES.append(cached := lru_cache(maxsize)(f))
        return cached

    return wrap


def _trim() -> None:
    """What this process has freed goes back to the system."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError, TypeError):  # a C library without it
        pass


def let_go(spark: SparkSession) -> None:
    """To be called on the driver between steps of many executions: what finished ones have left goes back to the system.

    Plans and small tables that were broadcast stay until the JVM needs the space, and its heap widens meanwhile.
    """
    _trim()
    spark.sparkContext._jvm.System.gc()


def enter(own=None) -> None:
    """To be called where an operator's part of a task begins: what other operators have left in the worker is let go.

    Workers serve one stage after the other, so without this each holds what all of them keep.
    """
    others = [c for c in _CACHES if c is not own and c.cache_info().currsize]
    for c in others:
        c.cache_clear()
    if others:
        _trim()


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir; a temporary folder is set only where it is unset and Spark runs in one process."""
    sc = spark.sparkContext
    found = sc.getCheckpointDir() or sc.getConf().get("spark.checkpoint.dir")
    if not found:
        if not sc.master.startswith("local[") and sc.master != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        found = tempfile.mkdtemp(prefix="webgather-")
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(found)
    return found


@contextmanager
def shuffles_removed(spark: SparkSession) -> Iterator[None]:
    """Shuffle files of the executions planned and run in it are removed when each ends."""
    before = spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    try:
        yield
    finally:
        spark.conf.unset(CLEANUP) if before is None else spark.conf.set(CLEANUP, before)


def written(df: DataFrame) -> DataFrame:
    """df as a Parquet table in the shared folder: later steps read it and survive lost executors.

    The table stands in for the shuffles it came from, so Spark is asked to remove their files
    when the write ends.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark).rstrip('/')}/tables/{uuid.uuid4().hex}"
    with shuffles_removed(spark):
        df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def hot_keys(groups: DataFrame, n_col: str, least: int = 1000, share: int = 1000) -> DataFrame | None:
    """The rows of groups with n_col above both `least` and one in `share` of its sum: under `share` rows, whatever the data. None if there are none."""
    total = groups.agg(F.sum(n_col)).first()[0] or 0
    hot = groups.filter(F.col(n_col) > max(least, total // share)).collect()
    return groups.sparkSession.createDataFrame(hot, groups.schema) if hot else None


def joined(rows: DataFrame, groups: DataFrame, keys: list[str], n_col: str, how: str = "inner") -> DataFrame:
    """rows with the columns of groups, whose keys are unique and whose n_col is how many rows have the key.

    A key of more than a thousandth of all rows is joined where its rows are, with a broadcast of
    under a thousand groups; what is shuffled has no such key.
    """
    hot = hot_keys(groups, n_col)
    if hot is None:
        return rows.join(groups, keys, how)
    rest = rows.join(F.broadcast(hot.select(*keys)), keys, "left_anti").join(groups, keys, how)
    return rest.unionByName(rows.join(F.broadcast(hot), keys))
