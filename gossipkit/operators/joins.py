"""As-of and interval joins by time, in bins: no key's rows meet in one task as such."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def micros(ts: Column) -> Column:
    """Microseconds of a timestamp with or without a zone."""
    return F.unix_micros(ts.cast("timestamp"))


def time_bin(ts: Column, seconds: int) -> Column:
    return F.floor(micros(ts) / F.lit(seconds * 1_000_000))


def as_of(left: DataFrame, right: DataFrame, key: str, ts: str, value: str, seconds: int = 86400) -> DataFrame:
    """left with the value of the latest row of right (of the same key, not later; the greatest value of equals), or
    null; rows without key or time stay and have none.

    A bin's rows are looked through together; what holds at a bin's start comes from one row for each earlier bin."""
    versions = right.filter(F.col(key).isNotNull() & F.col(ts).isNotNull()).groupBy(key, ts).agg(F.max(value).alias("_v")).withColumns({"_left": F.lit(None), "_side": F.lit(0)})
    asked = left.select(key, ts, F.lit(None).cast(right.schema[value].dataType).alias("_v"), F.struct(*left.columns).alias("_left"), F.lit(1).alias("_side"))
    rows = versions.withColumn("_left", F.lit(None).cast(asked.schema["_left"].dataType)).unionByName(asked).withColumn("_bin", time_bin(F.col(ts), seconds))
    inside = Window.partitionBy(key, "_bin").orderBy(ts, "_side").rowsBetween(Window.unboundedPreceding, 0)
    ends = rows.groupBy(key, "_bin").agg(F.max_by("_v", F.when(F.col("_side") == 0, F.col(ts))).alias("_end"))
    before = Window.partitionBy(key).orderBy("_bin").rowsBetween(Window.unboundedPreceding, -1)
    carried = ends.select(key, "_bin", F.last("_end", True).over(before).alias("_carry"))
    seen = rows.withColumn("_held", F.last("_v", True).over(inside)).filter("_side = 1")
    return seen.join(carried, [key, "_bin"], "left").select("_left.*", F.coalesce("_held", "_carry").alias(f"{value}_as_of"))


def interval(left: DataFrame, right: DataFrame, key: str, ts: str, seconds: int) -> DataFrame:
    """Pairs of one key with 0 <= right.ts - left.ts <= seconds, as structs a and b: an equi join on bins as wide as
    the interval, the left row standing in its own bin and the next one."""
    own = time_bin(F.col(ts), seconds)
    a = left.select(key, F.explode(F.array(own, own + 1)).alias("_bin"), F.struct(*left.columns).alias("a"))
    b = right.select(key, own.alias("_bin"), F.struct(*right.columns).alias("b"))
    gap = micros(F.col(f"b.{ts}")) - micros(F.col(f"a.{ts}"))
    return a.join(b, [key, "_bin"]).filter(gap.between(0, seconds * 1_000_000)).select("a", "b")
