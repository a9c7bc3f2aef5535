"""The recorder grid: r rows of 2^w recorder sketches, held sparsely as (row_id, col_id, rec, last_slot)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import grid_columns, rec_hash
from ..functions.params import GridParams
from .linear import with_estimate
from .recorder import in_window

CELL = ("row_id", "col_id")
#: Columns of a row of any sketch at most, for keys of one number.
_COLUMNS = 1 << 32


def scan_grid(df: DataFrame, p: GridParams, by: tuple[str, ...] = ()) -> DataFrame:
    """Contacts -> grid state. Repeats go before rows are multiplied by r, so that the shuffles are bounded by cores x m.

    The state is dealt by cell, so that counts by cell need no further exchange; a cell has at most m rows.
    """
    marks = df.select(*by, "core", rec_hash(F.col("opp"), p.m).alias("rec"), "slot").groupBy(*by, "core", "rec").agg(F.max("slot").alias("slot"))
    each = marks.select(*by, F.posexplode(grid_columns(F.col("core"), p)).alias("row_id", "col_id"), "rec", "slot")
    return each.groupBy(*by, F.col("row_id").cast("long").alias("row_id"), "col_id", "rec").agg(F.max("slot").alias("last_slot"))


def by_address(df: DataFrame, m: int, by: tuple[str, ...] = ()) -> DataFrame:
    """Contacts -> (by, k, word): touched recorders by address in 64-bit words; k is address x words of a sketch + place of the word.

    The part of a scan that does not depend on the sketch's rows. Stored, it serves several sketches of m recorders: they take it instead of contacts.
    """
    n, bit = (m + 63) // 64, F.expr("shiftleft(1L, cast(rec % 64 as int))")
    marks = df.select(*by, "core", rec_hash(F.col("opp"), m).alias("rec"))
    return marks.select(*by, (F.col("core") * F.lit(n) + F.expr("rec div 64")).alias("k"), bit.alias("word")).groupBy(*by, "k").agg(F.bit_or("word").alias("word"))


def _keyed(df: DataFrame, m: int, columns: Callable[[Column], Column], by: tuple[str, ...], dealt: bool = False) -> DataFrame:
    """(by, k, word): words of `packed` under one number for cell and place; with `dealt` all rows of a number are in one task whatever by is."""
    n = (m + 63) // 64
    own = df if "word" in df.columns else by_address(df, m, by)
    each = own.select(*by, F.posexplode(columns(F.expr(f"k div {n}"))).alias("row_id", "col_id"), (F.col("k") % n).alias("at"), "word")
    key = (F.col("row_id").cast("long") * F.lit(_COLUMNS) + F.col("col_id")) * F.lit(n) + F.col("at")
    each = each.select(*by, key.alias("k"), "word")
    return (each.repartition("k") if dealt else each).groupBy(*by, "k").agg(F.bit_or("word").alias("word"))


def _unkeyed(held: DataFrame, m: int, by: tuple[str, ...]) -> DataFrame:
    n = (m + 63) // 64
    cell = F.expr(f"k div {n}")
    return held.select(*by, F.shiftright(cell, 32).alias("row_id"), cell.bitwiseAND(F.lit(_COLUMNS - 1)).alias("col_id"), (F.col("k") % n).cast("int").alias("at"), "word")


def packed(df: DataFrame, m: int, columns: Callable[[Column], Column], by: tuple[str, ...] = ()) -> DataFrame:
    """Contacts, or these `by_address` -> (by, row_id, col_id, at, word): the touched recorders of each cell in 64-bit words, without their slots.

    For a recovery over the whole period, which asks only whether a recorder was touched. Bits are put together by address, before
    rows are multiplied by the rows of the sketch, and again by cell, where m / 64 words are the most; there is no row for each recorder.
    """
    return _unkeyed(_keyed(df, m, columns, by), m, by)


def scan_words(df: DataFrame, p: GridParams, by: tuple[str, ...] = ()) -> DataFrame:
    """As `scan_grid`, with the recorders of a cell in words (see `packed`)."""
    return packed(df, p.m, lambda core: grid_columns(core, p), by)


def scan_merged(df: DataFrame, p: GridParams, by: tuple[str, ...] = ("router",)) -> DataFrame:
    """The grids that `scan_words` makes for each value of by, merged by the nearest age. They are dealt by cell, so that merging needs no further exchange."""
    held = _keyed(df, p.m, lambda core: grid_columns(core, p), by, dealt=True)
    return _unkeyed(held.groupBy("k").agg(F.bit_or("word").alias("word")), p.m, ())


def words_of(state: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """A state with a row for each recorder as one in words; one in words as it is."""
    if "word" in state.columns:
        return state
    at, bit = F.expr("cast(rec div 64 as int)").alias("at"), F.expr("shiftleft(1L, cast(rec % 64 as int))")
    return state.groupBy(*by, *CELL, at).agg(F.bit_or(bit).alias("word"))


def scan_batches(df: DataFrame, p: GridParams, batch: int = 1 << 15) -> DataFrame:
    """As `scan_grid`, in buffers of `batch` contacts that are flushed when full and at the end of a slot."""
    w = Window.partitionBy("slot").orderBy("core", "opp", "router")
    parts = df.withColumn("batch", F.floor((F.row_number().over(w) - 1) / batch))
    return merge_grids(scan_grid(parts.withColumn("_slot", F.col("slot")), p, ("_slot", "batch")))


def grid_at(state: DataFrame, now: int, k: int) -> DataFrame:
    """The recorders young enough at the end of slot `now`, from a state of contacts up to then."""
    return state.filter(in_window(now, k))


def merge_grids(states: DataFrame, rule: str = "nearest", n: int | None = None, by: tuple[str, ...] = ()) -> DataFrame:
    """Grids of routers, shards or batches as one. 'farthest' keeps the larger age and so loses what one of n has not seen."""
    if "word" in states.columns:
        g = states.groupBy(*by, *CELL, "at")
        if rule == "nearest":
            return g.agg(F.bit_or("word").alias("word"))
        return g.agg(F.bit_and("word").alias("word"), F.count("*").alias("_n")).filter((F.col("_n") == n) & (F.col("word") != 0)).drop("_n")
    g = states.groupBy(*by, *CELL, "rec")
    if rule == "nearest":
        return g.agg(F.max("last_slot").alias("last_slot"))
    return g.agg(F.min("last_slot").alias("last_slot"), F.count("*").alias("_n")).filter(F.col("_n") == n).drop("_n")


def cells(state: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    touched = F.sum(F.bit_count("word")) if "word" in state.columns else F.count("*")
    return state.groupBy(*by, *CELL).agg(touched.alias("touched"))


def hot_cells(state: DataFrame, p: GridParams, by: tuple[str, ...] = ()) -> DataFrame:
    """Cells with at least the cut-off of touched recorders; at most r x 2^w rows for each value of by."""
    return cells(state, by).filter(F.col("touched") >= F.lit(p.cutoff))


def query_grid(state: DataFrame, cores: DataFrame, p: GridParams, by: tuple[str, ...] = ()) -> DataFrame:
    """(core) -> (core, touched, est, saturated): what all r cells of a known address have in common."""
    each = cores.select(*by, "core").distinct().select(*by, "core", F.posexplode(grid_columns(F.col("core"), p)).alias("row_id", "col_id"))
    met = each.withColumn("row_id", F.col("row_id").cast("long")).join(state, [*by, *CELL]).groupBy(*by, "core", "rec").agg(F.count("*").alias("n")).filter(F.col("n") == p.r)
    return with_estimate(met.groupBy(*by, "core").agg(F.count("*").alias("touched")), p.m)


def scan_sharded(df: DataFrame, p: GridParams, shards: int) -> DataFrame:
    """One grid for each residue of the address, in words, from contacts or these `by_address`."""
    core = F.expr(f"k div {(p.m + 63) // 64}") if "word" in df.columns else F.col("core")
    return scan_words(df.withColumn("shard", core % shards), p, ("shard",))


def age_grid(dense_rows: DataFrame, by: int = 1) -> DataFrame:
    """(.., age) -> older by some slots, up to 65,535; only for parity with the state that ages by itself."""
    return dense_rows.withColumn("age", F.least(F.col("age") + by, F.lit(65_535)))


def grid_memory(state: DataFrame, p: GridParams) -> DataFrame:
    """Bytes of a dense grid of 16-bit recorders, and the rows, cells and share that the sparse one holds."""
    dense = p.r * (1 << p.w) * p.m
    return state.agg(
        F.lit(2 * dense).cast("long").alias("dense_bytes"), F.count("*").alias("sparse_rows"), F.countDistinct(*CELL).alias("cells_used"),
        F.round(F.count("*") / F.lit(float(dense)), 9).alias("fill"),
    )
