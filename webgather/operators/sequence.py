"""Dense sequence numbers in a given order without a single-task window."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from webgather.operators.graph import step_table

def numbered(df: DataFrame, order: Sequence[str], name: str = "seq", partitions: int | None = None) -> DataFrame:
    """df with 1-based numbers by `order`; ties are numbered in any order, so order by all columns that matter.

    Rows are dealt by range into a fixed number of partitions and numbered in each; what earlier
    partitions hold is added from a table with one row a partition. The dealt rows are written, as
    the bounds of ranges are sampled and would differ where the deal is made twice.
    """
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    local = step_table(df.repartitionByRange(n, *order).sortWithinPartitions(*order).withColumn("_id", F.monotonically_increasing_id()))
    local = local.withColumn("_part", F.shiftright("_id", 33)).withColumn("_k", F.col("_id").bitwiseAND((1 << 33) - 1))
    counts = local.groupBy("_part").agg((F.max("_k") + 1).alias("_n"))
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    base = counts.select("_part", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_base"))
    return local.join(F.broadcast(base), "_part").withColumn(name, F.col("_base") + F.col("_k") + 1).drop("_id", "_part", "_k", "_base")


def running(df: DataFrame, order: Sequence[str], value: str, name: str, partitions: int | None = None) -> DataFrame:
    """df with the sum of `value` over all rows up to this one by `order`, which must tell rows apart; null values add nothing.

    Sums within ranges, and of whole ranges, as in `numbered`.
    """
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    local = step_table(df.repartitionByRange(n, *order).withColumn("_part", F.spark_partition_id()))
    sums = local.groupBy("_part").agg(F.coalesce(F.sum(value), F.lit(0)).alias("_n"))
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    base = sums.select("_part", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_base"))
    own = F.coalesce(F.sum(value).over(Window.partitionBy("_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)), F.lit(0))
    return local.withColumn("_own", own).join(F.broadcast(base), "_part").withColumn(name, F.col("_base") + F.col("_own")).drop("_part", "_own", "_base")
