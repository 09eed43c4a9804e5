"""The lane spill store: per-host FIFOs in an append-only log, refill, and compaction."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def append(df: DataFrame, order: str = "seq", host: str = "host", buckets: int = 64, segment: int = 1024) -> DataFrame:
    """host_bucket, segment, pos, host, seq: positions within a bucket's log, in order."""
    rows = df.select(F.col(host).alias("host"), F.col(order).alias("seq"), (F.col(host) % buckets).cast("int").alias("host_bucket"))
    pos = F.row_number().over(Window.partitionBy("host_bucket").orderBy("seq")) - 1
    return rows.withColumn("pos", pos.cast("long")).withColumn("segment", F.floor(F.col("pos") / segment))


def write(log: DataFrame, path: str, version: int) -> str:
    """A new version of the log under path: readers change over by name, so a lost writer harms none."""
    to = f"{path.rstrip('/')}/v{version}"
    log.repartition("host_bucket").sortWithinPartitions("host_bucket", "pos").write.partitionBy("host_bucket").mode("overwrite").parquet(to)
    return to


def next_pointers(log: DataFrame) -> DataFrame:
    """With next_pos, where the host's following URL stands."""
    return log.withColumn("next_pos", F.lead("pos").over(Window.partitionBy("host").orderBy("pos")))


def refill(log: DataFrame, hosts: DataFrame, quota: int) -> DataFrame:
    """Up to `quota` first URLs of each asked host, in order."""
    asked = log.join(hosts, "host", "left_semi")
    return asked.withColumn("k", F.row_number().over(Window.partitionBy("host").orderBy("pos"))).filter(F.col("k") <= quota)


def remaining(log: DataFrame, taken: DataFrame) -> DataFrame:
    return log.join(taken.select("host_bucket", "pos"), ["host_bucket", "pos"], "left_anti")


def used_ratio(live: DataFrame) -> DataFrame:
    """host_bucket, used, allocated (from the first to the last live segment's end), ratio."""
    per = live.groupBy("host_bucket").agg(F.count(F.lit(1)).alias("used"), (F.max("pos") - F.min("pos") + 1).alias("allocated"))
    return per.withColumn("ratio", F.round(F.col("used") / F.col("allocated"), 6))


def compact(live: DataFrame, threshold: float = 0.5, segment: int = 1024) -> DataFrame:
    """The log with the buckets under the threshold packed from their start; order by position stays. moved: whether a row has."""
    ratio = used_ratio(live).filter(F.col("used") / F.col("allocated") < threshold).select("host_bucket", F.lit(True).alias("packs"))
    rows = live.join(F.broadcast(ratio), "host_bucket", "left")
    packed = F.row_number().over(Window.partitionBy("host_bucket").orderBy("pos")) - 1
    pos = F.when(F.col("packs"), packed).otherwise(F.col("pos"))
    return rows.withColumn("new_pos", pos.cast("long")).withColumn("moved", F.col("new_pos") != F.col("pos")).select("host_bucket", "host", "seq", F.col("pos").alias("old_pos"), F.col("new_pos").alias("pos"), F.floor(F.col("new_pos") / segment).alias("segment"), "moved")


def order_kept(memory: DataFrame, disk: DataFrame) -> DataFrame:
    """faults: hosts in which a URL in memory was found after one on disk."""
    a, b = memory.groupBy("host").agg(F.max("seq").alias("a")), disk.groupBy("host").agg(F.min("seq").alias("b"))
    return a.join(b, "host").agg(F.count_if(F.col("a") > F.col("b")).alias("faults"), F.count(F.lit(1)).alias("hosts"))


def static_queues(df: DataFrame, queues: int, fails_every: int, host: str = "host", order: str = "seq") -> DataFrame:
    """Baseline: a fixed number of physical queues; every n-th read of a queue fails and goes to its end.

    host, items, inversions: how often a later URL of the host comes before an earlier one.
    """
    rows = df.select(F.col(host).alias("host"), F.col(order).alias("seq"), (F.col(host) % queues).alias("queue"))
    k = F.row_number().over(Window.partitionBy("queue").orderBy("seq"))
    n = F.count(F.lit(1)).over(Window.partitionBy("queue"))
    served = rows.withColumn("at", F.when(k % fails_every == 0, k + n).otherwise(k))
    before = F.lag("seq").over(Window.partitionBy("host").orderBy("at"))
    return served.withColumn("x", before > F.col("seq")).groupBy("host").agg(F.count(F.lit(1)).alias("items"), F.count_if("x").alias("inversions"))


def by_priority(df: DataFrame, priority: str, host: str = "host", order: str = "seq") -> DataFrame:
    """Baseline: a key-value store that serves a host's URLs by priority, not by age."""
    return df.withColumn("k", F.row_number().over(Window.partitionBy(host).orderBy(F.col(priority).desc(), order)))
