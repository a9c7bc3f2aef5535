"""Exact deduplication by distributed MSD radix partitioning.

Groups are split by successive blocks of bytes. A row leaves the recursion when nothing else has
its bytes so far or when its text has ended; rows that end together are equal, without any digest.
Blocks grow 16-fold, so the number of rounds is the logarithm of the longest text.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import BLANKS, dropped, stored, whole

FIRST_BLOCK, GROWTH = 256, 16
#: Bytes of repeated blocks that are sent to all tasks at most; more are joined by a shuffle.
SEND = 32 << 20


def squeezed(text: str | Column = "text") -> Column:
    """Text with each run of white space as one blank; null is the empty text."""
    return F.regexp_replace(whole(text), BLANKS, " ")


def radix_groups(rows: DataFrame, key: str = "doc_id", body: str = "body", first: int = FIRST_BLOCK, growth: int = GROWTH, send: int = SEND) -> DataFrame:
    """rows(key, body binary not null, ...) -> the other columns, keep_id (smallest key of the rows with an equal body) and group_size.

    Every input row comes out once. Rows that repeat a key or have none count as rows of their group; keep_id is null
    only where no row of the group has a key. Groups are told apart by a number of their own, never by a key. Empty input: no rows.
    Counts are combined before the shuffle; the repeated blocks are stored and, up to `send` bytes of them, sent to
    the rows, so that no body is shuffled. Beyond that rows are joined by block, where Spark can split a hot group. Only rows still
    undecided go on. Columns named _gid, _block, _first, _next, _n or _open are not for the caller.
    """
    spark, extra = rows.sparkSession, [c for c in rows.columns if c != body]
    done: list[DataFrame] = []
    active = rows.withColumn("_gid", F.lit(0).cast("long"))
    at, size = 1, first
    while True:
        cut = active.withColumn("_block", F.substring(body, at, size))
        counted = cut.groupBy("_gid", "_block").agg(F.min(key).alias("_first"), F.count("*").alias("_n")).filter("_n > 1")
        repeats, repeats_path = stored(counted.withColumn("_next", F.monotonically_increasing_id()))
        heavy = repeats.agg(F.coalesce(F.sum(F.length("_block") + 48), F.lit(0))).first()[0]
        ended = F.length(body) < at + size - 1
        step, _ = stored(
            cut.join(F.broadcast(repeats) if heavy <= send else repeats.hint("merge"), ["_gid", "_block"], "left")
            .withColumn("_open", F.col("_n").isNotNull() & ~ended)
            .select(
                *extra,
                F.when(F.col("_open"), F.col(body)).alias(body),
                F.col("_next").alias("_gid"),
                F.when(F.col("_n").isNull(), F.col(key)).otherwise(F.col("_first")).alias("keep_id"),
                F.coalesce("_n", F.lit(1)).cast("long").alias("group_size"),
                "_open",
            )
        )
        dropped(spark, repeats_path)
        done.append(step.filter("not _open").select(*extra, "keep_id", "group_size"))
        active = step.filter("_open").select(*extra, body, "_gid")
        at, size = at + size, size * growth
        if active.isEmpty():
            return reduce(DataFrame.unionByName, done)


def exact_dedup(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """documents -> one row per input row: key, keep_id, group_size, kept, text_sha256 (of the normalised text; an output only).

    Texts are equal when identical after squeezing white space. Null text is the empty text; a row without a
    key is grouped like any other but never the smallest unless all are without (then keep_id is null and kept true).
    Rows that repeat the smallest key of a group are all kept, as a key stands for one document.
    Other columns are ignored, whatever their names. Empty input: no rows.
    """
    base = docs.select(F.col(key).alias("doc_id"), squeezed(text).alias("_t")).select(
        "doc_id", F.sha2(F.col("_t").cast("binary"), 256).alias("text_sha256"), F.col("_t").cast("binary").alias("body")
    )
    out = radix_groups(base)
    return out.select("doc_id", "keep_id", "group_size", F.expr("doc_id <=> keep_id").alias("kept"), "text_sha256")
