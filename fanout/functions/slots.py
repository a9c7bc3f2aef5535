"""Slots and windows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def micros(ts: Column) -> Column:
    """Microseconds of a time since 1970, whatever the session's zone, for TIMESTAMP_NTZ in UTC."""
    return F.unix_micros(ts.cast("timestamp"))


def slot_of(ts: Column, origin: str, seconds: int) -> Column:
    """Number of the slot of `seconds` since the origin (text, UTC)."""
    start = F.unix_micros(F.lit(origin + " UTC").cast("timestamp"))
    return F.floor((micros(ts) - start) / F.lit(seconds * 1_000_000)).cast("long")


def windows(spark: SparkSession, n: int, k: int) -> DataFrame:
    """All windows of k of n slots, by their first slot."""
    return spark.range(max(0, n - k + 1)).select(F.col("id").alias("win"))


def expand_windows(df: DataFrame, n: int, k: int) -> DataFrame:
    """Each contact once for every window that has its slot: up to k rows for one; for small inputs and checks."""
    low, high = F.greatest(F.col("slot") - (k - 1), F.lit(0)), F.least(F.col("slot"), F.lit(n - k))
    return df.filter((low <= high) & (F.col("slot") >= 0) & (F.col("slot") < n)).withColumn("win", F.explode(F.sequence(low.cast("long"), high.cast("long"))))


def coverage(df: DataFrame, keys: list[str], n: int, k: int) -> DataFrame:
    """(keys, slot) -> (keys, lo, hi): disjoint ranges of windows in which the key occurs; at most one row for an occurrence."""
    w = Window.partitionBy(*keys).orderBy("slot")
    seen = df.filter((F.col("slot") >= 0) & (F.col("slot") < n)).select(*keys, "slot").distinct()
    before = F.lag("slot").over(w)
    ranges = seen.select(*keys, F.greatest(F.col("slot") - (k - 1), F.lit(0), F.coalesce(before + 1, F.lit(0))).alias("lo"), F.least(F.col("slot"), F.lit(n - k)).alias("hi"))
    return ranges.filter("lo <= hi")


def steps(ranges: DataFrame, keys: list[str], least: float = 1) -> DataFrame:
    """(keys, lo, hi) ranges -> (keys, lo, hi, n): how many ranges of a key cover the windows lo..hi, where at least `least` do.

    Ends are summed before the shuffle; the running sum is sorted by key, so its cost does not depend on the span.
    """
    ends = ranges.select(*keys, F.explode(F.array(F.struct(F.col("lo").alias("at"), F.lit(1).alias("by")), F.struct((F.col("hi") + 1).alias("at"), F.lit(-1).alias("by")))).alias("e"))
    sums = ends.groupBy(*keys, F.col("e.at").alias("lo")).agg(F.sum("e.by").alias("by")).filter("by != 0")
    w = Window.partitionBy(*keys).orderBy("lo")
    run = sums.withColumn("n", F.sum("by").over(w)).withColumn("hi", F.lead("lo").over(w) - 1)
    return run.filter((F.col("n") >= F.lit(least)) & F.col("hi").isNotNull()).select(*keys, "lo", "hi", "n")


def joined_ranges(ranges: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, lo, hi) disjoint -> the same with ranges that touch put together."""
    w = Window.partitionBy(*keys).orderBy("lo")
    part = ranges.withColumn("_new", F.when(F.lag("hi").over(w) + 1 >= F.col("lo"), 0).otherwise(1)).withColumn("_part", F.sum("_new").over(w))
    return part.groupBy(*keys, "_part").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi")).drop("_part")


def expand_ranges(ranges: DataFrame) -> DataFrame:
    """(.., lo, hi, ..) -> a row with `win` for every window of the range."""
    return ranges.withColumn("win", F.explode(F.sequence("lo", "hi"))).drop("lo", "hi")


def fixed_window(df: DataFrame, k: int, n: int) -> DataFrame:
    """Contacts with `win`, the number of their block of k slots; only whole blocks of n slots."""
    return df.filter((F.col("slot") >= 0) & (F.col("slot") < n - n % k)).withColumn("win", F.floor(F.col("slot") / k).cast("long"))
