"""Exact fan-out: the yardstick for every sketch."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.slots import coverage, expand_ranges, expand_windows, fixed_window, steps


def exact_fanout(df: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(core, opp) -> (core, fan_out). Pairs are made distinct before they are counted, so no task holds a set."""
    return df.select(*by, "core", "opp").distinct().groupBy(*by, "core").agg(F.count("*").alias("fan_out"))


def exact_sets(df: DataFrame) -> DataFrame:
    """(core, sorted counterparts); a row is as large as its fan-out."""
    return df.groupBy("core").agg(F.array_sort(F.collect_set("opp")).alias("opps"))


def racy_count(df: DataFrame, worker: str = "router") -> DataFrame:
    """What workers count together if none sees the sets of the others: a negative control."""
    return exact_fanout(df, (worker,)).groupBy("core").agg(F.sum("fan_out").alias("fan_out"))


def exact_heavy(df: DataFrame, theta: int) -> DataFrame:
    return exact_fanout(df).filter(F.col("fan_out") >= theta)


def exact_heavy_fixed(df: DataFrame, theta: int, k: int, n: int) -> DataFrame:
    """(win, core, fan_out) of blocks of k slots."""
    return exact_fanout(fixed_window(df, k, n), ("win",)).filter(F.col("fan_out") >= theta)


def exact_heavy_sliding(df: DataFrame, theta: int, k: int, n: int, how: str = "sweep") -> DataFrame:
    """(win, core, fan_out) of every sliding window: by a sweep over coverage ranges, or by expansion for checks."""
    if how == "expand":
        return exact_fanout(expand_windows(df.select("core", "opp", "slot"), n, k), ("win",)).filter(F.col("fan_out") >= theta)
    heavy = steps(coverage(df, ["core", "opp"], n, k), ["core"], theta)
    return expand_ranges(heavy).select("win", "core", F.col("n").alias("fan_out"))


def detection_delay(df: DataFrame, theta: int, k: int, n: int) -> DataFrame:
    """core -> end of the first sliding window and of the first fixed block that report it, and the slots between them.

    Fixed values are null for cores that no block reports.
    """
    sliding = steps(coverage(df, ["core", "opp"], n, k), ["core"], theta).groupBy("core").agg((F.min("lo") + (k - 1)).alias("sliding_slot"))
    fixed = exact_heavy_fixed(df, theta, k, n).groupBy("core").agg(((F.min("win") + 1) * k - 1).alias("fixed_slot"))
    return sliding.join(fixed, "core", "left").withColumn("delay", F.col("fixed_slot") - F.col("sliding_slot"))


def traffic_profile(df: DataFrame, theta: int, by: str = "win") -> DataFrame:
    """For each window: contacts, different cores, counterparts and pairs, and heavy cores."""
    fan = exact_fanout(df, (by,))
    size = df.groupBy(by).agg(F.count("*").alias("contacts"), F.countDistinct("opp").alias("opps"))
    return size.join(fan.groupBy(by).agg(F.count("*").alias("cores"), F.sum("fan_out").alias("pairs"), F.count_if(F.col("fan_out") >= theta).alias("heavy")), by)


def heavy_transitions(heavy: DataFrame) -> DataFrame:
    """(win, core) of sliding windows -> for each window how many cores entered, left and stayed since the one before."""
    now = heavy.select("win", "core", F.lit(1).alias("a"))
    old = heavy.select((F.col("win") + 1).alias("win"), "core", F.lit(1).alias("b"))
    both = now.join(old, ["win", "core"], "full")
    return both.groupBy("win").agg(F.count_if(F.col("b").isNull()).alias("entered"), F.count_if(F.col("a").isNull()).alias("gone"), F.count_if(F.col("a").isNotNull() & F.col("b").isNotNull()).alias("stayed"))
