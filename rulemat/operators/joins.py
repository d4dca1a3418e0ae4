"""Joins that plain equi-joins do not cover: range, interval, as-of, skewed keys."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def binned(left: DataFrame, right: DataFrame, at: str, low: str, high: str, width: float) -> DataFrame:
    """Rows of ``left`` whose ``at`` lies in [low, high] of a row of ``right``: an equi-join on
    bins instead of a nested loop.  ``right`` rows repeat once per bin they touch."""
    bin_of = lambda c: F.floor(c / F.lit(width))
    spread = right.withColumn("_bin", F.explode(F.sequence(bin_of(F.col(low)), bin_of(F.col(high)))))
    return left.withColumn("_bin", bin_of(F.col(at))).join(spread, "_bin").where(F.col(at).between(F.col(low), F.col(high))).drop("_bin")


def as_of(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, take: list[str]) -> DataFrame:
    """Each left row with the latest right row of its key at or before its time: one union and
    one ordered window, no join and no loop."""
    blank = [F.lit(None).cast(dict(right.dtypes)[c]).alias(c) for c in take]
    a = left.select("*", F.col(left_time).alias("_t"), F.lit(1).alias("_side"), *blank)
    rest = [F.lit(None).cast(t).alias(c) for c, t in left.dtypes if c != key]
    b = right.select(F.col(key), *rest, F.col(right_time).alias("_t"), F.lit(0).alias("_side"), *take)
    w = Window.partitionBy(key).orderBy("_t", "_side").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b)
    for c in take:
        both = both.withColumn(c, F.last(c, ignorenulls=True).over(w))
    return both.where("_side = 1").drop("_t", "_side")


def salted(large: DataFrame, small: DataFrame, key: str, salts: int) -> DataFrame:
    """Equi-join that deals every key of the large side over ``salts`` partitions and repeats
    the small side as often."""
    a = large.withColumn("_salt", F.pmod(F.xxhash64(*large.columns), F.lit(salts)))
    b = small.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1)).cast("array<bigint>")))
    return a.join(b, [key, "_salt"]).drop("_salt")


def bounded_broadcast(df: DataFrame, max_rows: int = 1_000_000) -> DataFrame:
    """Broadcast hint only for a side whose size has been checked; beyond it, as it is."""
    return F.broadcast(df) if df.limit(max_rows + 1).count() <= max_rows else df


def tagged(condition: Column, name: str) -> Column:
    return condition.cast("int").alias(name)
