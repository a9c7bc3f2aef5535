"""Competing detectors: a sketch rebuilt by the Chinese remainder theorem, one by slices of the address, a shared pool of bits."""

from __future__ import annotations

from math import prod

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import POOL, mixed, rec_hash
from ..functions.params import ADDRESS_BITS, GridParams, hot_cutoff
from ..sources.storage import stored
from .chains import by_remainders, by_slices, cell_bits
from .grid import cells, packed
from .linear import with_estimate

#: Pairwise prime numbers of columns, near 2^14 and near 2^11.
MODULI, SMALL_MODULI = (16381, 16369, 16363), (2039, 2053, 2063)


def crt_scan(df: DataFrame, m: int, moduli: tuple[int, ...] = MODULI, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, row_id, col_id, rec): set bits of the cell core mod prime of each row."""
    marks = df.select(*by, "core", rec_hash(F.col("opp"), m).alias("rec")).distinct()
    each = marks.select(*by, F.posexplode(F.array(*(F.col("core") % q for q in moduli))).alias("row_id", "col_id"), "rec")
    return each.select(*by, F.col("row_id").cast("long").alias("row_id"), "col_id", "rec").distinct()


def crt_words(df: DataFrame, m: int, moduli: tuple[int, ...] = MODULI, by: tuple[str, ...] = ()) -> DataFrame:
    """As `crt_scan`, with the bits of a cell in words."""
    return packed(df, m, lambda core: F.array(*(core % q for q in moduli)), by)


def crt_regain(state: DataFrame, m: int, theta: int, moduli: tuple[int, ...] = MODULI, by: tuple[str, ...] = ()) -> DataFrame:
    """(core, touched, est, saturated): hot cells are combined row by row over the bits they share, and end below the cut-off.

    Each hot cell is one row of bits. All pairs of rows 0 and 1 are tried; the remainders of a pair leave 2^32 / (p0 p1) addresses,
    17 with the large primes, so the cells of the further rows follow from these. Values of more than 32 bits are no addresses.
    """
    if prod(moduli) < 1 << ADDRESS_BITS:
        raise ValueError("the product of the primes has to cover the address")
    hot = stored(cells(state, by).filter(F.col("touched") >= F.lit(hot_cutoff(m, theta))))
    return with_estimate(by_remainders(cell_bits(state, hot, m, by), GridParams(m=m, r=len(moduli), theta=theta), moduli, by), m)


def slice_scan(df: DataFrame, p: GridParams, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, row_id, col_id, rec): cells are slices of the bare address, without any hash to spread them; rows 1..r-1."""
    marks = df.select(*by, "core", rec_hash(F.col("opp"), p.m).alias("rec")).distinct()
    cut = F.array(*(F.shiftright("core", p.shift(i)).bitwiseAND(F.lit(p.mask)) for i in range(1, p.r)))
    each = marks.select(*by, F.posexplode(cut).alias("row_id", "col_id"), "rec")
    return each.select(*by, (F.col("row_id") + 1).cast("long").alias("row_id"), "col_id", "rec").distinct()


def slice_words(df: DataFrame, p: GridParams, by: tuple[str, ...] = ()) -> DataFrame:
    """As `slice_scan`, with the bits of a cell in words."""
    cut = packed(df, p.m, lambda core: F.array(*(F.shiftright(core, p.shift(i)).bitwiseAND(F.lit(p.mask)) for i in range(1, p.r))), by)
    return cut.withColumn("row_id", F.col("row_id") + 1)


def slice_regain(state: DataFrame, p: GridParams, by: tuple[str, ...] = ()) -> DataFrame:
    """(core, touched, est, saturated) from chains of slices that overlap and share enough bits."""
    hot = stored(cells(state, by).filter(F.col("touched") >= F.lit(p.cutoff)))
    return with_estimate(by_slices(cell_bits(state, hot, p.m, by), p, by), p.m)


def _spot(core, virtual, bits: int):
    """Position in the pool of a core's virtual bit."""
    return mixed(core.bitwiseXOR((virtual * F.lit(2654435761)).bitwiseAND(F.lit(0xFFFFFFFF))), POOL) % F.lit(bits)


def pool_scan(df: DataFrame, bits: int, s: int, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, bit): the set bits of a pool that all cores share; each core owns s virtual positions."""
    return df.select(*by, "core", rec_hash(F.col("opp"), s).alias("v")).distinct().select(*by, _spot(F.col("core"), F.col("v"), bits).alias("bit")).distinct()


def pool_words(pool: DataFrame, bits: int, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, bit) -> (by, words, free): the pool as 64-bit words, bits / 8 bytes a row whatever the traffic, and its share of clear bits."""
    word = pool.groupBy(*by, F.expr("cast(bit div 64 as int)").alias("at")).agg(F.bit_or(F.expr("shiftleft(1L, cast(bit % 64 as int))")).alias("word"))
    set_bits = F.sum(F.bit_count("word")).alias("n")
    held = word.groupBy(*by).agg(F.array_sort(F.collect_list(F.struct("at", "word"))).alias("w"), set_bits)
    # words that are clear are filled in: the gap before each set word, and the one at the end
    prev = lambda i: F.when(i == 0, F.lit(-1)).otherwise(F.get("w", i - 1)["at"])
    gap = lambda n: F.array_repeat(F.lit(0).cast("long"), n)
    full = F.flatten(F.transform("w", lambda x, i: F.concat(gap(x["at"] - prev(i) - 1), F.array(x["word"]))))
    full = F.concat(full, gap(F.lit((bits + 63) // 64 - 1) - F.element_at("w", -1)["at"]))
    return held.select(*by, full.alias("words"), (F.lit(1.0) - F.col("n") / F.lit(float(bits))).alias("free"))


#: Bytes of all pools together that are sent to all tasks at most.
POOL_SEND = 64 << 20


def pool_query(pool: DataFrame, cores: DataFrame, bits: int, s: int, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, core) of a stored list -> (core, touched, est): virtual bits that are set, less what the pool's fill explains.

    A pool has a fixed size, so its words go to the rows of the list, whose positions are tested and counted in place: the list
    is dealt by core already. Cores without a set bit are left out. Pools of very many `by` values are joined by bit instead.
    """
    own = F.greatest(F.lit(s) - F.col("touched"), F.lit(1)).cast("double") / F.lit(float(s))
    parts = int(cores.sparkSession.conf.get("spark.sql.shuffle.partitions"))  # each core is s tests: its rows are few, its work is not
    listed, virtual = cores.select(*by, "core").distinct().repartition(parts, *by, "core"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(s - 1).cast("long")))
    pools = pool.select(*by).distinct().count() if by else 1
    if pools * bits // 8 <= POOL_SEND:
        words = F.broadcast(stored(pool_words(pool, bits, by)))
        met = listed.join(words, [*by]) if by else listed.crossJoin(words)  # one row without `by`
        each = met.withColumn("v", virtual).withColumn("bit", _spot(F.col("core"), F.col("v"), bits))
        hits = each.filter(F.getbit(F.get("words", F.shiftright("bit", 6).cast("int")), F.col("bit").bitwiseAND(63).cast("int")) == 1)
        seen = hits.groupBy(*by, "core").agg(F.count("*").alias("touched"), F.first("free").alias("free"))
    else:
        each = listed.withColumn("v", virtual).withColumn("bit", _spot(F.col("core"), F.col("v"), bits))
        hits = each.join(pool, [*by, "bit"]).groupBy(*by, "core").agg(F.count("*").alias("touched"))
        fill = pool.groupBy(*by).agg((F.lit(1.0) - F.count("*") / F.lit(float(bits))).alias("free"))
        seen = hits.join(fill, [*by]) if by else hits.crossJoin(fill)
    return seen.select(*by, "core", "touched", F.round(F.lit(float(s)) * F.log("free") - F.lit(float(s)) * F.log(own), 6).alias("est"))


def pool_regain(df: DataFrame, bits: int, s: int, theta: int, by: tuple[str, ...] = ()) -> DataFrame:
    """Cores of the whole list whose estimate reaches theta."""
    return pool_query(stored(pool_scan(df, bits, s, by)), df, bits, s, by).filter(F.col("est") >= theta)


def builtin_ndv(df: DataFrame, kind: str = "hll") -> DataFrame:
    """(core, est) by the engine's own sketches: 'approx', 'hll' or 'theta'."""
    how = {
        "approx": F.approx_count_distinct("opp"),
        "hll": F.hll_sketch_estimate(F.hll_sketch_agg("opp")),
        "theta": F.theta_sketch_estimate(F.theta_sketch_agg("opp")),
    }[kind]
    return df.groupBy("core").agg(how.cast("long").alias("est"))
