"""Ranks and running sums without a global window: rows fall into coarse buckets, bucket totals are summed, and only
rows of one bucket are ordered together."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F


def running_sum(df: DataFrame, value: Column, keys: list[str], bucket: Column, order: list[Column], name: str) -> DataFrame:
    """Adds `name`: the sum of `value` over the rows before a row, in (bucket, order) order within keys.

    Bucket totals are few rows; the sum over them is the only step that is ordered by keys alone."""
    rows = df.withColumns({"_b": bucket, "_v": value})
    totals = rows.groupBy(*keys, "_b").agg(F.sum("_v").alias("_t"))
    before = Window.partitionBy(*(keys or [F.lit(0)])).orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    totals = totals.select(*(F.col(k).alias(f"_k{i}") for i, k in enumerate(keys)), F.col("_b").alias("_b2"), F.coalesce(F.sum("_t").over(before), F.lit(0)).alias("_before"))
    within = Window.partitionBy(*keys, "_b").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("_own", F.coalesce(F.sum("_v").over(within), F.lit(0)))
    on = F.col("_b") == F.col("_b2")
    for i, k in enumerate(keys):
        on = on & (F.col(k) == F.col(f"_k{i}"))
    joined = rows.join(totals, on)
    return joined.select(*df.columns, (F.col("_before") + F.col("_own")).cast("long").alias(name))


def numbered(df: DataFrame, keys: list[str], bucket: Column, order: list[Column], name: str, first: int = 0) -> DataFrame:
    """Adds `name`: dense numbers from `first` in (bucket, order) order within keys."""
    return running_sum(df, F.lit(1), keys, bucket, order, "_n").withColumn(name, F.col("_n") + first).drop("_n")
