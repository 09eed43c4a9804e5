"""Each row with the last row of another table at or before its time."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def join(left: DataFrame, right: DataFrame, key: str, time: str, columns: Sequence[str]) -> DataFrame:
    """left with the columns of the last row of right that has its key and isn't later; null if none.

    Both sides go through one sort by key and time, so nothing is paired.
    """
    a = left.withColumn("_right", F.lit(1)).withColumn("_v", F.lit(None).cast(right.select(F.struct(*columns).alias("s")).schema["s"].dataType))
    b = right.select(key, time, F.struct(*columns).alias("_v"), F.lit(0).alias("_right"))
    w = Window.partitionBy(key).orderBy(time, "_right").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b, allowMissingColumns=True).withColumn("_last", F.last("_v", ignorenulls=True).over(w))
    return both.filter("_right = 1").select(*left.columns, *(F.col(f"_last.{c}").alias(c) for c in columns))
