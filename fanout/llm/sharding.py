"""Sharding by best-fit-decreasing packing of indivisible groups of equal texts.

The packing runs over the histogram of group weights: equal weights are placed together, since the
tightest bin that fits stays the tightest until it is full. D different weights need a total of at
least D(D+1)/2 bytes, so the histogram of T bytes has at most sqrt(2T) rows.
"""

from __future__ import annotations

from bisect import bisect_left, insort
from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import HOT_KEYS, checkpointed, dropped, looked_up, stored, whole

#: Rows of the packing or of the numbering that are sent to all tasks at most; more are joined by a shuffle.
SEND_ROWS = 200_000


def best_fit(weights: Sequence[tuple[int, int]], capacity: int, bins: int | None = None) -> list[tuple[int, int, int]] | None:
    """(weight, how many) by falling weight -> (weight, bin, how many); None if more than `bins` bins are needed.

    The open bins are kept in order of remaining room (the balanced tree; ties: the lower number).
    Weights beyond the capacity never fit.
    """
    rooms: list[tuple[int, int]] = []
    placed, opened = [], 0
    for w, left in weights:
        if w > capacity:
            return None
        while left:
            i = bisect_left(rooms, (w, -1))
            if i == len(rooms):
                if bins is not None and opened == bins:
                    return None
                room, name = capacity, opened
                opened += 1
            else:
                room, name = rooms.pop(i)
            n = min(left, room // w) if w else left
            placed.append((w, name, n))
            insort(rooms, (room - n * w, name))
            left -= n
    return placed


def pack(weights: Sequence[tuple[int, int]], bins: int) -> list[tuple[int, int, int]]:
    """Best-fit-decreasing into `bins` bins at the smallest capacity found by bisection from the mean upwards."""
    weights = sorted(weights, reverse=True)
    if not weights:
        return []
    total = sum(w * n for w, n in weights)
    low = max(-(-total // bins), weights[0][0])
    high = low
    while best_fit(weights, high, bins) is None:
        high += max(1, (high - low), low >> 12)
    while low < high:
        mid = (low + high) // 2
        low, high = (low, mid) if best_fit(weights, mid, bins) is not None else (mid + 1, high)
    return best_fit(weights, high, bins)


def numbered(rows: DataFrame, *keys: str) -> DataFrame:
    """rows with `nth`, gapless from 0 for each value of `keys`, whatever its share of the rows.

    Rows are sorted inside their partitions and stored; then only the count of each (partition, key) is needed. A running
    sum of these over the partitions of a key gives where each begins.
    """
    held = checkpointed(rows.sortWithinPartitions(*keys)).withColumn("_at", F.monotonically_increasing_id())
    held = held.withColumn("_part", F.shiftright("_at", 33)).withColumn("_row", F.col("_at").bitwiseAND((1 << 33) - 1))
    counts = held.groupBy("_part", *keys).agg(F.count("*").alias("_n"), F.min("_row").alias("_low"))
    before = Window.partitionBy(*keys).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    shift, _ = stored(counts.select("_part", *keys, (F.coalesce(F.sum("_n").over(before), F.lit(0)) - F.col("_low")).alias("_base")))
    shift = F.broadcast(shift) if shift.count() <= SEND_ROWS else shift.hint("merge")
    return held.join(shift, ["_part", *keys]).withColumn("nth", F.col("_row") + F.col("_base")).drop("_part", "_row", "_at", "_base")


def shard_groups(groups: DataFrame, bins: int) -> DataFrame:
    """groups(key, weight long > 0, ...) -> the same with `shard`. Keys must be unique; groups should be a stored table.

    The driver holds the histogram of weights. What it finds goes back to the groups by weight, sent to all tasks up to
    SEND_ROWS rows. Beyond that the weights that many groups share (fewer than HOT_KEYS) are still sent, the others shuffled.
    """
    spark = groups.sparkSession
    seen = groups.groupBy("weight").agg(F.count("*").alias("n")).toPandas()
    plan = pack(list(zip(seen["weight"].tolist(), seen["n"].tolist())), bins)
    often, total = dict(zip(seen["weight"].tolist(), seen["n"].tolist())), int(seen["n"].sum())

    def by_weight(rows: DataFrame, found: list[tuple], kinds: str) -> DataFrame:
        if len(found) <= SEND_ROWS:
            return rows.join(F.broadcast(spark.createDataFrame(found, kinds)), "weight")
        hot = [f for f in found if often[f[0]] * HOT_KEYS > total]
        few, rest = F.broadcast(spark.createDataFrame(hot, kinds)), spark.createDataFrame([f for f in found if often[f[0]] * HOT_KEYS <= total], kinds)
        return rows.join(few, "weight").unionByName(rows.join(few.select("weight").distinct(), "weight", "left_anti").join(rest.hint("merge"), "weight"))

    merged: dict[int, list[list[int]]] = {}
    for w, b, n in plan:
        spans = merged.setdefault(w, [])
        if spans and spans[-1][0] == b:
            spans[-1][1] += n
        else:
            spans.append([b, n])
    spans = []
    for w, s in merged.items():
        at = 0
        for b, n in s if len(s) > 1 else ():
            spans.append((w, b, at, at + n))
            at += n
    out = by_weight(groups, [(w, s[0][0]) for w, s in merged.items() if len(s) == 1], "weight long, shard int")
    if spans:
        shared = by_weight(groups, [(w,) for w in sorted({s[0] for s in spans})], "weight long")
        ranked = by_weight(numbered(shared, "weight"), spans, "weight long, shard int, low long, high long").filter("nth >= low and nth < high")
        out = out.unionByName(ranked.drop("nth", "low", "high"))
    return out


def shard(docs: DataFrame, bins: int = 8, key: str = "doc_id", text: str = "text") -> DataFrame:
    """documents -> doc_id, size, text_crc32, law ('bytes'), shard 0..bins-1, slot gapless from 0 in each shard, grown_shard (null).

    Size is the UTF-8 bytes of the text (null: none) plus 1. Equal texts are one group and stay together; a null
    text is equal to the empty one. Groups weigh what their rows weigh together, and a group heavier than the mean
    shard has a shard of its own size. Repeated rows are rows of their group. Empty input: no rows.
    """
    base = docs.select(F.col(key).alias("doc_id"), whole(text).cast("binary").alias("_b")).select(
        "doc_id", (F.length("_b") + 1).cast("long").alias("size"), F.crc32("_b").alias("text_crc32"), F.unhex(F.sha2("_b", 256)).alias("_key")
    )
    base, _ = stored(base)
    groups, groups_path = stored(base.groupBy("_key").agg(F.sum("size").alias("weight"), F.count("*").alias("_n")))
    where, _ = stored(shard_groups(groups, bins).select("_key", "shard", "_n"))
    dropped(docs.sparkSession, groups_path)
    rows = looked_up(base, where, "_key").drop("_key")
    return numbered(rows, "shard").select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", F.col("nth").alias("slot"), F.lit(None).cast("int").alias("grown_shard")
    )
