"""The live side: contacts arrive as a stream, slots close, heavy addresses are reported.

State is a maximum by recorder, so repeats, retries and late contacts of a slot that open windows still cover change nothing
that they should not. Recovery needs all rows of an address together and so runs on the merged state, for all slots that a batch closes at once.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.hashing import encode_key, grid_columns, rec_hash
from ..functions.params import GridParams
from ..functions.slots import slot_of
from ..operators.recover import regain_touches, touches
from ..sources.contacts import EVENT_ORIGIN, EVENT_SLOT
from ..sources.storage import dropped, names, shared_dir, stored, table


def replayed(spark: SparkSession, sf_dir: str, arrival: Column, n: int) -> str:
    """The events as n files in a folder of shared storage, one after the other by `arrival` (0..n-1), as they would land. Rows without one do not."""
    path = f"{shared_dir(spark)}/landing/{uuid.uuid4().hex}"
    land(table(spark, sf_dir, "events").withColumn("_at", arrival), path, range(n))
    return path


def land(events: DataFrame, path: str, numbers: Iterable[int]) -> None:
    """Adds the events of these arrivals to a folder, a file each."""
    for i in numbers:
        events.filter(F.col("_at") == i).drop("_at").coalesce(1).write.mode("append").parquet(path)


def event_stream(spark: SparkSession, sf_dir: str, landing: str | None = None) -> DataFrame:
    """The events as a stream with a time that takes a watermark, and contact columns of the key and the user.

    From the table, or from the files of a landing folder in the order of their times, one to a micro-batch.
    """
    reader = spark.readStream.schema(table(spark, sf_dir, "events").schema)
    raw = reader.option("maxFilesPerTrigger", 1).parquet(landing) if landing else reader.option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.select(
        F.col("ts").cast("timestamp").alias("ts"), encode_key(F.get_json_object("props", "$.k").cast("long")).alias("core"), F.col("user_id").alias("opp"),
        slot_of(F.col("ts"), EVENT_ORIGIN, EVENT_SLOT).alias("slot"), "event_type", "event_id",
    )


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """All that is there now through the streaming engine, as a table in shared storage."""
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/streams/{uuid.uuid4().hex}"
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/log").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{base}/out")
    # complete: each batch replaces the result of the one before
    last: list[str] = []

    def keep(batch: DataFrame, number: int) -> None:
        path = f"{base}/batch={number}"
        batch.write.mode("overwrite").parquet(path)
        last.append(path)

    stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{base}/log").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(last[-1]) if last else spark.createDataFrame([], stream.schema)


def slot_counts(stream: DataFrame, width: str = "12 minutes", delay: str = "12 minutes") -> DataFrame:
    """Contacts of each closed slot and core."""
    return stream.withWatermark("ts", delay).groupBy(F.window("ts", width), "core").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "core", "n")


def sliding_fanout(stream: DataFrame, length: str, slide: str, delay: str = "1 hour") -> DataFrame:
    """Exact fan-out of closed sliding windows: pairs are made distinct in each window, then counted; two stateful steps."""
    pairs = stream.withWatermark("ts", delay).select(F.window("ts", length, slide).alias("window"), "core", "opp").dropDuplicates(["window", "core", "opp"])
    return pairs.groupBy("window", "core").agg(F.count("*").alias("fan_out")).select(F.col("window.start").alias("start"), "core", "fan_out")


def sessions(stream: DataFrame, gap: str = "6 hours", delay: str = "1 hour") -> DataFrame:
    """Bursts of a core without a pause of `gap`."""
    return stream.withWatermark("ts", delay).groupBy(F.session_window("ts", gap), "core").agg(F.count("*").alias("n")).select(F.col("session_window.start").alias("start"), "core", "n")


def distinct_contacts(stream: DataFrame, delay: str = "12 minutes") -> DataFrame:
    """Each (core, opp, slot) once within the horizon."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["core", "opp", "slot"]).select("core", "opp", "slot")


def grid_state(stream: DataFrame, p: GridParams) -> DataFrame:
    """The grid as running state: the last slot of each recorder; for output mode complete or update."""
    marks = stream.select(F.posexplode(grid_columns(F.col("core"), p)).alias("row_id", "col_id"), rec_hash(F.col("opp"), p.m).alias("rec"), "slot")
    return marks.groupBy(F.col("row_id").cast("long").alias("row_id"), "col_id", "rec").agg(F.max("slot").alias("last_slot"))


def dense_state(stream: DataFrame, m: int, span_seconds: int | None = None, delay: str = "1 hour") -> DataFrame:
    """The dense alternative: for each core one array of m last slots (-1: never) as keyed state, emitted when it changes.

    With `span_seconds` a core that the watermark has passed by so much since its last contact is forgotten, and comes out
    once more with `expired`; a contact after that begins anew.
    """

    def fold(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            yield pd.DataFrame({"core": [key[0]], "last": [[]], "expired": [True]})
            return
        last, seen = (np.array(state.get[0], np.int64), state.get[1]) if state.exists else (np.full(m, -1, np.int64), 0)
        for part in parts:
            np.maximum.at(last, part["rec"].to_numpy(), part["slot"].to_numpy())
            seen = max(seen, int(part["ms"].max()))
        state.update((last.tolist(), seen))
        if span_seconds is not None:
            state.setTimeoutTimestamp(max(seen + 1_000 * span_seconds, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({"core": [key[0]], "last": [last.tolist()], "expired": [False]})

    marks = stream.withWatermark("ts", delay) if span_seconds is not None else stream
    marks = marks.select("core", rec_hash(F.col("opp"), m).alias("rec"), "slot", F.unix_millis("ts").alias("ms"), "ts")
    timeout = GroupStateTimeout.NoTimeout if span_seconds is None else GroupStateTimeout.EventTimeTimeout
    return marks.groupBy("core").applyInPandasWithState(fold, "core long, last array<long>, expired boolean", "last array<long>, seen long", "update", timeout)


def on_time(stream: DataFrame, key: str, delay: str = "1 hour") -> tuple[DataFrame, int]:
    """The rows of the stream, drained, that are not later than the watermark, each key once; and how many were dropped for that."""
    spark = stream.sparkSession
    base, kept = f"{shared_dir(spark)}/streams/{uuid.uuid4().hex}", stream.withWatermark("ts", delay).dropDuplicates([key, "ts"])
    q = kept.writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/log").trigger(availableNow=True).start()
    q.awaitTermination()
    late = sum(o.numRowsDroppedByWatermark for r in q.recentProgress for o in r.stateOperators)
    return spark.read.schema(kept.schema).parquet(f"{base}/out"), late


def in_memory(stream: DataFrame, mode: str = "append") -> DataFrame:
    """A stream, drained into a table of the driver's memory: for reports of a few rows, such as counts by router."""
    name = f"live_{uuid.uuid4().hex}"
    stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", f"{shared_dir(stream.sparkSession)}/streams/{name}").trigger(availableNow=True).start().awaitTermination()
    return stream.sparkSession.table(name)


def newest(stream: DataFrame, key: str) -> DataFrame:
    """A stream of updates, drained: the last row of each key."""
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/streams/{uuid.uuid4().hex}"
    keep = lambda batch, number: batch.withColumn("_batch", F.lit(number).cast("long")).write.mode("overwrite").parquet(f"{base}/out/part={number}")
    stream.writeStream.outputMode("update").foreachBatch(keep).option("checkpointLocation", f"{base}/log").trigger(availableNow=True).start().awaitTermination()
    rows = spark.read.parquet(f"{base}/out").drop("part")
    rest = [c for c in stream.columns if c != key]
    return rows.groupBy(key).agg(*(F.max_by(c, "_batch").alias(c) for c in rest))


def merged_routers(streams: list[DataFrame]) -> DataFrame:
    out = streams[0]
    for s in streams[1:]:
        out = out.unionByName(s)
    return out


class SlotReporter:
    """foreachBatch target: a report for every slot that a batch closes, over the window of p.k slots that ends with it.

    The state, the last touch of each recorder, is a table in shared storage for each batch number, and so are the reports: a
    batch that is run again writes the same tables anew, and a reporter made after a restart goes on from the last batch that
    was finished. A batch may close any number of slots; they are worked out together in one plan over ranges of windows.
    A contact of a slot that is closed already counts in the windows still to come. What no later window can count is forgotten.
    """

    def __init__(self, p: GridParams, base: str):
        self.p, self.base = p, base

    def __call__(self, batch: DataFrame, number: int) -> None:
        spark, p = batch.sparkSession, self.p
        before = max((int(n) for n in names(spark, f"{self.base}/closed") if n.isdigit() and int(n) < number), default=None)
        new, closed = stored(touches(batch, p)), -1
        if before is not None:
            closed = spark.read.parquet(f"{self.base}/closed/{before}").first()["slot"]
            new = spark.read.parquet(f"{self.base}/state/{before}").withColumnRenamed("last_slot", "slot").unionByName(new)
        last = new.agg(F.max("slot")).first()[0]
        last = max(closed, -1 if last is None else last)
        first = max(0, closed - p.k + 2)
        if last - p.k + 1 >= first:
            found = regain_touches(new, p, last + 1, first)
            found.select((F.col("win") + p.k - 1).alias("slot"), "core", "touched", "est", "saturated").write.mode("overwrite").parquet(f"{self.base}/out/part={number}")
        state = new.groupBy("row_id", "col_id", "rec").agg(F.max("slot").alias("last_slot")).filter(F.col("last_slot") > last - p.k)
        state.write.mode("overwrite").parquet(f"{self.base}/state/{number}")
        spark.createDataFrame([(last,)], "slot long").coalesce(1).write.mode("overwrite").parquet(f"{self.base}/closed/{number}")
        old = [n for n in names(spark, f"{self.base}/state") if n.isdigit() and before is not None and int(n) < before]
        dropped(spark, *(f"{self.base}/state/{n}" for n in old))


def heavy_report(stream: DataFrame, p: GridParams, base: str | None = None) -> DataFrame:
    """(slot, core, touched, est, saturated): the reports of all slots closed so far, by the batches that are there now.

    With the same `base` a later call goes on where an earlier one, of this process or of another, has ended.
    """
    spark = stream.sparkSession
    base = base or f"{shared_dir(spark)}/streams/{uuid.uuid4().hex}"
    stream.writeStream.foreachBatch(SlotReporter(p, base)).option("checkpointLocation", f"{base}/log").trigger(availableNow=True).start().awaitTermination()
    schema = "slot long, core long, touched long, est double, saturated boolean"
    return spark.read.schema(schema).parquet(f"{base}/out").select("slot", "core", "touched", "est", "saturated") if names(spark, f"{base}/out") else spark.createDataFrame([], schema)
