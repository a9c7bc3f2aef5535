"""Recorder sketches: for each recorder the last slot that touched it. Ages are now - last_slot, so ageing writes nothing."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import rec_hash
from ..functions.params import MAX_AGE
from ..functions.slots import coverage, steps
from .linear import with_estimate


def touch(df: DataFrame, m: int, keys: tuple[str, ...] = ("core",), salt: int = 0) -> DataFrame:
    """Contacts -> (keys, rec, last_slot). A maximum: order, repeats and late contacts make no difference."""
    return df.select(*keys, rec_hash(F.col("opp"), m, salt).alias("rec"), "slot").groupBy(*keys, "rec").agg(F.max("slot").alias("last_slot"))


def in_window(now: int, k: int) -> Column:
    age = F.lit(now) - F.col("last_slot")
    return (age >= 0) & (age < k)


def touched(state: DataFrame, now: int, k: int, keys: tuple[str, ...] = ("core",)) -> DataFrame:
    """How many recorders of each key are younger than k at the end of slot `now`."""
    return state.filter(in_window(now, k)).groupBy(*keys).agg(F.count("*").alias("touched"))


def recorder_estimate(state: DataFrame, now: int, k: int, m: int) -> DataFrame:
    return with_estimate(touched(state, now, k), m)


def all_windows(df: DataFrame, m: int, k: int, n: int, keys: tuple[str, ...] = ("core",), least: float = 1) -> DataFrame:
    """(keys, lo, hi, n): touched recorders in every sliding window, as steps."""
    marks = df.select(*keys, rec_hash(F.col("opp"), m).alias("rec"), "slot")
    return steps(coverage(marks, [*keys, "rec"], n, k), [*keys], least)


def combine_farthest(states: DataFrame, n: int, keys: tuple[str, ...] = ()) -> DataFrame:
    """Of n states the largest age of each recorder: young only where all are. A recorder that one lacks is lost."""
    return states.groupBy(*keys, "rec").agg(F.min("last_slot").alias("last_slot"), F.count("*").alias("_n")).filter(F.col("_n") == n).drop("_n")


def combine_nearest(states: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """The smallest age of each recorder: young where any is. The merge of routers, shards and partial states."""
    return states.groupBy(*keys, "rec").agg(F.max("last_slot").alias("last_slot"))


def compact(state: DataFrame, now: int, k: int) -> DataFrame:
    """The state without recorders that no window from `now` on can count."""
    return state.filter(F.col("last_slot") > now - min(k, MAX_AGE))


def empty_sketch(m: int) -> Column:
    """A dense sketch that nothing has touched."""
    return F.array_repeat(F.lit(MAX_AGE), m)


def aged(ages: Column, by: int = 1) -> Column:
    """A dense sketch some slots later; ages stop at 65,535."""
    return F.transform(ages, lambda x: F.least(x + by, F.lit(MAX_AGE)))


def dense(state: DataFrame, now: int, m: int, keys: tuple[str, ...] = ("core",)) -> DataFrame:
    """(keys, ages): sparse state as arrays of m ages."""
    some = state.filter(F.col("last_slot") <= now).withColumn("age", F.least(F.lit(now) - F.col("last_slot"), F.lit(MAX_AGE)).cast("int"))
    held = some.groupBy(*keys).agg(F.map_from_entries(F.collect_list(F.struct(F.col("rec").cast("int"), "age"))).alias("_m"))
    return held.withColumn("ages", F.transform(F.sequence(F.lit(0), F.lit(m - 1)), lambda i: F.coalesce(F.try_element_at("_m", i), F.lit(MAX_AGE)))).drop("_m")
