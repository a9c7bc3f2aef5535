"""Contact streams (core, opp, slot, router) over the given tables."""

from __future__ import annotations

from math import sqrt

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import encode_key, key32
from ..functions.slots import slot_of
from .storage import table

EVENT_ORIGIN, EVENT_SLOT, EVENT_SLOTS = "2024-01-01 00:00:00", 720, 3_600
SHIP_ORIGIN, SHIP_SLOT, SHIP_SLOTS = "1995-01-01 00:00:00", 30 * 86_400, 84
#: Thresholds. (table, rows, spread, least, most): with l = rows of the table / rows, l + spread * sqrt(l) within bounds, so that any
#: folder has its own; the most is the published threshold. Events are l contacts of a key in each block of 300 slots, evenly, and
#: heavy keys stand out by the spread. A number: suppliers grow with their table and their fan-out does not.
THETA: dict[str, tuple[str, float, float, int, int] | int] = {"F1": ("events", 1_200.0, 1.7, 4, 1_024), "F3": 110, "F3_all": 540, "F6": ("documents", 7.8125, 0.0, 32, 1_024)}


def theta(spark: SparkSession, sf_dir: str, fixture: str) -> int:
    """The fixture's threshold for the tables of a folder, from the number of rows in their footers."""
    rule = THETA[fixture]
    if isinstance(rule, int):
        return rule
    name, rows, spread, least, most = rule
    load = table(spark, sf_dir, name).count() / rows
    return min(most, max(least, int(load + spread * sqrt(load))))


def ranked(df: DataFrame, name: str, out: str) -> DataFrame:
    """df with the rank from 0 of its value in a column of few different values; the window runs over these only."""
    values = df.select(name).distinct().withColumn(out, F.row_number().over(Window.orderBy(name)).cast("long") - 1)
    return df.join(values, name)


def to_contacts(df: DataFrame, core: Column, opp: Column, slot: Column, router: Column) -> DataFrame:
    """The fixed schema; rows without core, opp or slot are left out (see `dropped_contacts`)."""
    out = df.select(core.cast("long").alias("core"), opp.cast("long").alias("opp"), slot.cast("long").alias("slot"), router.cast("long").alias("router"))
    return out.filter("core is not null and opp is not null and slot is not null")


def dropped_contacts(df: DataFrame, core: Column, opp: Column, slot: Column) -> DataFrame:
    """How many rows `to_contacts` leaves out."""
    return df.agg(F.count_if(core.isNull() | opp.isNull() | slot.isNull()).alias("dropped"))


def both_directions(packets: DataFrame, is_core: Column) -> DataFrame:
    """(src, dst, slot, router) -> contacts: the side for which is_core holds of src is the core, else dst."""
    return to_contacts(packets, F.when(is_core, F.col("src")).otherwise(F.col("dst")), F.when(is_core, F.col("dst")).otherwise(F.col("src")), F.col("slot"), F.col("router"))


def swap_roles(contacts: DataFrame) -> DataFrame:
    return contacts.select(F.col("opp").alias("core"), F.col("core").alias("opp"), "slot", "router")


def tokens(text: str = "text") -> Column:
    return F.array_distinct(F.regexp_extract_all(F.lower(F.col(text)), F.lit("[a-z]+"), F.lit(0)))


def _f1(s, d):
    e = ranked(table(s, d, "events"), "event_type", "router")
    return to_contacts(e, encode_key(F.get_json_object("props", "$.k").cast("long")), F.col("user_id"), slot_of(F.col("ts"), EVENT_ORIGIN, EVENT_SLOT), F.col("router"))


def _f2(s, d):
    e = ranked(table(s, d, "events"), "event_type", "router")
    return to_contacts(e, encode_key(F.col("user_id")), F.get_json_object("props", "$.k").cast("long"), slot_of(F.col("ts"), EVENT_ORIGIN, EVENT_SLOT), F.col("router"))


def _f3(s, d):
    return to_contacts(table(s, d, "lineitem"), encode_key(F.col("l_suppkey")), F.col("l_partkey"), slot_of(F.col("l_shipdate"), SHIP_ORIGIN, SHIP_SLOT), F.col("l_linenumber") % 4)


def _f4(s, d):
    j = table(s, d, "lineitem").join(table(s, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    return to_contacts(j, encode_key(F.col("l_suppkey")), F.col("o_custkey"), slot_of(F.col("o_orderdate"), SHIP_ORIGIN, SHIP_SLOT), F.col("l_linenumber") % 4)


def _f5(s, d):
    j = table(s, d, "lineitem").join(table(s, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    return to_contacts(j, encode_key(F.col("o_custkey")), F.col("l_partkey"), slot_of(F.col("o_orderdate"), SHIP_ORIGIN, SHIP_SLOT), F.col("o_orderkey") % 4)


def spread(df: DataFrame) -> DataFrame:
    """df dealt to all cores where its scan has fewer parts than cores (a small table of one row group); otherwise as it is."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() < cores else df


def _tokens_of(docs: DataFrame) -> DataFrame:
    t = ranked(spread(docs.select("doc_id", "source", "text")), "source", "router").select("doc_id", "router", F.explode(tokens()).alias("token"))
    return to_contacts(t, key32(F.col("token")), F.col("doc_id"), F.expr("doc_id div 10"), F.col("router"))


def _f6(s, d):
    return _tokens_of(table(s, d, "documents"))


def _f7(s, d):
    p = table(s, d, "pages").select("page_id", "url", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href"))
    host = F.regexp_extract("url", "^[a-z]+://([^/]+)", 1)
    return to_contacts(p, key32(host), key32(F.col("href")), F.expr("page_id div 10"), F.col("page_id") % 4)


def _f8(s, d):
    t = ranked(spread(table(s, d, "conversations").select("conv_id", "turn", "role", "text")), "role", "router").select("conv_id", "turn", "router", F.explode(tokens()).alias("token"))
    return to_contacts(t, key32(F.col("token")), F.col("conv_id"), F.col("turn"), F.col("router"))


def _f9(s, d):
    toxic = table(s, d, "labels").filter("toxic = 1").select("doc_id")
    return _tokens_of(table(s, d, "documents").join(toxic, "doc_id", "left_semi"))


def packets(s: SparkSession, d: str) -> DataFrame:
    """Both directions: suppliers are the cores, a return flag A sends from them."""
    away, supp, part = F.col("l_returnflag") == "A", encode_key(F.col("l_suppkey")), F.col("l_partkey")
    return table(s, d, "lineitem").select(
        F.when(away, supp).otherwise(part).alias("src"), F.when(away, part).otherwise(supp).alias("dst"),
        slot_of(F.col("l_shipdate"), SHIP_ORIGIN, SHIP_SLOT).alias("slot"), (F.col("l_linenumber") % 4).alias("router"), away.alias("away"),
    )


FIXTURES = {"F1": _f1, "F2": _f2, "F3": _f3, "F4": _f4, "F5": _f5, "F6": _f6, "F7": _f7, "F8": _f8, "F9": _f9}


def contacts(spark: SparkSession, sf_dir: str, fixture: str) -> DataFrame:
    return FIXTURES[fixture](spark, sf_dir)
