"""Relational operators that users of an index need around it, in forms that stay partitioned."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F


def as_of(left: DataFrame, right: DataFrame, key: str, value: str, width: int) -> DataFrame:
    """left with `value` of right's last row at or before its integer `key`; null if there is none.

    Both sides fall into ranges of `width` keys; a range gets the last value of the ranges before it, so that windows
    run within ranges only."""
    l = left.select("*", F.floor(F.col(key) / F.lit(width)).alias("_b"), F.lit(1).alias("_side"), F.lit(None).cast(right.schema[value].dataType).alias("_v"))
    last = right.groupBy(F.floor(F.col(key) / F.lit(width)).alias("_b")).agg(F.max_by(value, key).alias("_last"))
    ranges = l.select("_b").distinct().unionByName(last.select("_b")).distinct().join(last, "_b", "left")
    before = Window.partitionBy(F.lit(0)).orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    carry = ranges.select("_b", F.last("_last", ignorenulls=True).over(before).alias("_carry"))
    r = right.select(F.col(key), F.floor(F.col(key) / F.lit(width)).alias("_b"), F.lit(0).alias("_side"), F.col(value).alias("_v"))
    both = l.unionByName(r, allowMissingColumns=True)
    w = Window.partitionBy("_b").orderBy(key, "_side").rowsBetween(Window.unboundedPreceding, 0)
    seen = both.withColumn(value, F.last("_v", ignorenulls=True).over(w)).where("_side = 1")
    return seen.join(carry, "_b").withColumn(value, F.coalesce(value, "_carry")).drop("_b", "_side", "_v", "_carry")


def range_join(points: DataFrame, ranges: DataFrame, point: str, low: str, high: str, width: int) -> DataFrame:
    """Rows with low <= point <= high, by equal buckets: a range is listed in each bucket that it touches."""
    b = lambda c: F.floor(F.col(c) / F.lit(width))
    left = points.withColumn("_b", b(point))
    right = ranges.withColumn("_b", F.explode(F.sequence(b(low), b(high))))
    return left.join(right, "_b").where(F.col(point).between(F.col(low), F.col(high))).drop("_b")


def interval_join(left: DataFrame, right: DataFrame, left_at: str, right_at: str, span: int) -> DataFrame:
    """Rows whose integer times satisfy right_at - span <= left_at < right_at: equal buckets of `span`, own and next."""
    l = left.withColumn("_b", F.explode(F.array(F.floor(F.col(left_at) / F.lit(span)), F.floor(F.col(left_at) / F.lit(span)) + 1)))
    r = right.withColumn("_b", F.floor(F.col(right_at) / F.lit(span)))
    return l.join(r, "_b").where((F.col(left_at) < F.col(right_at)) & (F.col(left_at) >= F.col(right_at) - span)).drop("_b")


def salted_join(left: DataFrame, right: DataFrame, key: str, salts: int, hash_of: Column) -> DataFrame:
    """An inner join with a hot key on the left: its rows are spread over `salts` keys, the right side is repeated."""
    l = left.withColumn("_s", F.pmod(hash_of, F.lit(salts)))
    r = right.withColumn("_s", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return l.join(r, [key, "_s"]).drop("_s")


def observed(df: DataFrame, name: str, *columns: str):
    """(df, observation): row count and column sums that are gathered while df runs, without a pass of their own."""
    from pyspark.sql import Observation

    seen = Observation(name)
    return df.observe(seen, F.count(F.lit(1)).alias("rows"), *(F.sum(c).alias(c) for c in columns)), seen
