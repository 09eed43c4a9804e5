"""Streaming twins: once-filter, polite lanes, windows over a replayed table."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from webgather.operators.graph import shared_folder


def replay(spark: SparkSession, table: DataFrame, folder: str, files: int, order: str) -> DataFrame:
    """A stream over `table`, one file a batch, by equal ranges of the number `order`.

    The files are written one after the other: a stream takes them by their age.
    """
    low, high = table.agg(F.min(order), F.max(order)).first()
    step = (((high or 0) - (low or 0)) // files) + 1
    for k in range(files):
        own = table.filter((F.col(order) >= (low or 0) + k * step) & (F.col(order) < (low or 0) + (k + 1) * step))
        own.coalesce(1).sortWithinPartitions(order).write.mode("append").parquet(folder)
    return spark.readStream.schema(table.schema).option("maxFilesPerTrigger", 1).parquet(folder)


def run(stream: DataFrame, mode: str = "append", seconds: int = 120) -> DataFrame:
    """All that a stream gives over what there is now, by way of a Parquet sink or, for other modes, memory."""
    spark = stream.sparkSession
    base = shared_folder(spark)
    place = f"{base.rstrip('/')}/streams/{uuid.uuid4().hex}"
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{place}/state").trigger(availableNow=True)
    name = f"s{uuid.uuid4().hex}"
    q = writer.format("parquet").option("path", f"{place}/out").start() if mode == "append" else writer.format("memory").queryName(name).start()
    if not q.awaitTermination(seconds):
        q.stop()
        raise TimeoutError(f"the stream ran over {seconds} s")
    return spark.read.schema(stream.schema).parquet(f"{place}/out") if mode == "append" else spark.table(name)


def once(stream: DataFrame, key: str) -> DataFrame:
    """Each key at its first arrival; state holds all keys."""
    return stream.dropDuplicates([key])


def once_within(stream: DataFrame, key: str, time: str, horizon: str) -> DataFrame:
    """Each key at most once in the horizon: bounded state, and keys that come again later come out again."""
    return stream.withWatermark(time, horizon).dropDuplicatesWithinWatermark([key])


def once_by_table(stream: DataFrame, key: str, path: str, seconds: int = 120) -> DataFrame:
    """Exact and of bounded state: each batch is folded, cut by what the table has, and appended under its number."""
    spark = stream.sparkSession

    def merge(batch: DataFrame, number: int) -> None:
        new = batch.dropDuplicates([key])
        try:
            seen = spark.read.option("basePath", path).parquet(path).filter(F.col("batch") != number)
            new = new.join(seen.select(key).distinct(), key, "left_anti")
        except Exception as e:  # the first batch finds no table
            if "PATH_NOT_FOUND" not in str(e):
                raise
        new.write.mode("overwrite").parquet(f"{path}/batch={number}")

    q = stream.writeStream.foreachBatch(merge).option("checkpointLocation", f"{path}-state").trigger(availableNow=True).start()
    if not q.awaitTermination(seconds):
        q.stop()
        raise TimeoutError(f"the stream ran over {seconds} s")
    return spark.read.parquet(path)


def polite(stream: DataFrame, delay_us: int) -> DataFrame:
    """seq, host, start_us: earliest polite starts; the state of a host is its next permissible instant."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        next_at = state.get[0] if state.exists else -(1 << 62)
        rows = pd.concat(list(batches)).sort_values("seq")
        starts = []
        for arrive in rows["arrive_us"].tolist():
            start = max(arrive, next_at)
            starts.append(start)
            next_at = start + delay_us
        state.update((next_at,))
        yield pd.DataFrame({"seq": rows["seq"], "host": key[0], "start_us": starts})

    return stream.select("seq", "host", "arrive_us").groupBy("host").applyInPandasWithState(step, "seq long, host long, start_us long", "next_at long", "append", GroupStateTimeout.NoTimeout)
