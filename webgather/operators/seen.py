"""Once-filters: each distinct element leaves exactly once. The exact one and its alternatives.

All take rows with a key and a sequence number stamped when the element was discovered.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from webgather.functions.fingerprints import fp60


def exact(df: DataFrame, key: str = "key", seq: str = "seq") -> DataFrame:
    """key and first_seq; equal keys of a task are folded before the shuffle."""
    return df.groupBy(key).agg(F.min(seq).alias("first_seq"))


def batched(df: DataFrame, batch_rows: int, known: DataFrame | None = None, key: str = "key", seq: str = "seq") -> DataFrame:
    """key, first_seq, flush, release_seq: elements leave when the buffer of `batch_rows` that took them is merged.

    known: fingerprints (fp) of earlier rounds. The set is the exact one's; only the release is later.
    """
    first = exact(df, key, seq).withColumn("fp", fp60(key))
    if known is not None:
        first = first.join(known, "fp", "left_anti")
    total = df.agg(F.max(seq).alias("n"))
    flush = F.ceil(F.col("first_seq") / batch_rows)
    return first.crossJoin(F.broadcast(total)).select(key, "first_seq", flush.alias("flush"), F.least(flush * batch_rows, F.col("n")).alias("release_seq"))


def release_lag(released: DataFrame) -> DataFrame:
    lag = F.col("release_seq") - F.col("first_seq")
    return released.agg(F.count(F.lit(1)).alias("released"), F.max("flush").alias("flushes"), F.sum(lag).cast("long").alias("lag_total"), F.max(lag).alias("lag_most"))


def flush_costs(released: DataFrame, batch_rows: int) -> DataFrame:
    """Per flush: elements released, and bytes of known hashes read and written in sequence."""
    per = released.groupBy("flush").agg(F.count(F.lit(1)).alias("new"))
    before = F.coalesce(F.sum("new").over(Window.orderBy("flush").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return per.select("flush", "new", (8 * before).alias("known_read"), (8 * (before + F.col("new"))).alias("known_write"))


def valued(df: DataFrame, key: str = "key", seq: str = "seq", value: str = "value", op: str = "op") -> DataFrame:
    """seq, key, op, verdict, old_value: check, update or check_update against what came before; the latest value counts."""
    order = Window.partitionBy(key).orderBy(seq)
    stored = F.when(F.col(op) != "check", F.col(value))
    old = F.last(stored, ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, -1))
    verdict = F.when(F.row_number().over(order) == 1, "UNIQUE").otherwise("DUPLICATE")
    return df.select(seq, key, op, F.when(F.col(op) != "update", verdict).alias("verdict"), F.when(F.col(op) == "check_update", old).alias("old_value"))


def repository(df: DataFrame, buckets: int, key: str = "key", seq: str = "seq", value: str = "value", op: str = "op") -> DataFrame:
    """bucket, key, value of all keys that were ever seen; value is null where a key was only checked."""
    stored = F.when(F.col(op) != "check", F.col(value))
    latest = F.max_by(stored, F.when(stored.isNotNull(), F.col(seq)))
    return df.groupBy((fp60(key) % buckets).alias("bucket"), key).agg(latest.alias(value))


def valued_with(df: DataFrame, repo: DataFrame, buckets: int, key: str = "key", seq: str = "seq", value: str = "value", op: str = "op") -> DataFrame:
    """As `valued`, of rows that come after what is in the repository, which is joined bucket by bucket."""
    known = repo.select("bucket", F.col(key), F.col(value).alias("_stored"), F.lit(True).alias("_known"))
    own = valued(df, key, seq, value, op).withColumn("bucket", fp60(key) % buckets).join(known, ["bucket", key], "left")
    old = F.when(F.col(op) == "check_update", F.coalesce("old_value", "_stored"))
    verdict = F.when(F.col("verdict").isNotNull() & F.col("_known"), "DUPLICATE").otherwise(F.col("verdict"))
    return own.select(seq, key, op, verdict.alias("verdict"), old.alias("old_value"))


def stored_values(df: DataFrame, key: str = "key", seq: str = "seq", value: str = "value", op: str = "op") -> DataFrame:
    """The repository after all operations."""
    return df.filter(F.col(op) != "check").groupBy(key).agg(F.max_by(value, seq).alias("value"))


def order_inversions(first: DataFrame, host: Column, buckets: int, key: str = "key") -> DataFrame:
    """Per host, how often an element that was found later leaves earlier because its bucket does."""
    rows = first.select(host.alias("host"), "first_seq", (fp60(key) % buckets).alias("bucket"))
    before = F.lag("bucket").over(Window.partitionBy("host").orderBy("first_seq"))
    return rows.withColumn("inverted", F.coalesce(before > F.col("bucket"), F.lit(False))).groupBy("host").agg(F.count(F.lit(1)).alias("elements"), F.count_if("inverted").alias("inversions"))


def bloom_size(n: int, p: float) -> tuple[int, int]:
    """(bits, hashes) for n elements at false-positive rate p."""
    bits = math.ceil(-n * math.log(p) / math.log(2) ** 2)
    return bits, max(1, round(bits / n * math.log(2)))


def bloom(df: DataFrame, bits: int, hashes: int, key: str = "key", seq: str = "seq") -> DataFrame:
    """key, first_seq, released: what a queue with a Bloom filter lets through, in parallel.

    With m(b) the least sequence number that touches bit b, an element is lost exactly if all
    its bits have an earlier one: bits are set whether or not an element is released.
    """
    first = exact(df, key, seq)
    h1, h2 = fp60(key), fp60(key, 1)
    step = h2 + 1 - h2 % 2
    touched = first.select(key, "first_seq", F.explode(F.transform(F.sequence(F.lit(0), F.lit(hashes - 1)), lambda i: (h1 + i * step) % bits)).alias("bit"))
    least = touched.groupBy("bit").agg(F.min("first_seq").alias("m"))
    return touched.join(least, "bit").groupBy(key, "first_seq").agg((F.max("m") == F.col("first_seq")).alias("released"))


def fingerprint_set(df: DataFrame, bits: int, key: str = "key", seq: str = "seq") -> DataFrame:
    """fp, key, first_seq of what a dictionary of truncated hashes keeps."""
    first = exact(df, key, seq).withColumn("fp", fp60(key) % (1 << bits))
    return first.groupBy("fp").agg(F.min_by(key, "first_seq").alias(key), F.min("first_seq").alias("first_seq"))
