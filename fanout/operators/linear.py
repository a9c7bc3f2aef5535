"""Bitmap estimates for fixed windows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import estimate, rec_hash
from ..functions.slots import expand_windows, fixed_window


def linear_touched(df: DataFrame, m: int, by: tuple[str, ...] = (), salt: int = 0) -> DataFrame:
    """Set bits of each core's bitmap, as distinct (core, bit) rows that are counted."""
    bits = df.select(*by, "core", rec_hash(F.col("opp"), m, salt).alias("rec")).distinct()
    return bits.groupBy(*by, "core").agg(F.count("*").alias("touched"))


def with_estimate(df: DataFrame, m: int) -> DataFrame:
    return df.withColumn("est", estimate(F.col("touched"), m)).withColumn("saturated", F.col("touched") >= m)


def linear_estimate(df: DataFrame, m: int, by: tuple[str, ...] = (), impl: str = "rows") -> DataFrame:
    """(core, opp) -> (core, touched, est, saturated); impl 'bitmap' keeps a bitmap of 4 KB for each core while aggregating."""
    if impl == "rows":
        return with_estimate(linear_touched(df, m, by), m)
    if m > 32_768:
        raise ValueError("a native bitmap has 32,768 bits")
    spot = F.bitmap_bit_position(rec_hash(F.col("opp"), m) + 1)  # the helper counts from 1
    return with_estimate(df.groupBy(*by, "core").agg(F.bitmap_count(F.bitmap_construct_agg(spot)).alias("touched")), m)


def linear_salted(df: DataFrame, m: int, salts: int = 4) -> DataFrame:
    """(core, est): the mean over independent recorder hashes, against collisions that all cores share."""
    out = None
    for s in range(salts):
        e = with_estimate(linear_touched(df, m, salt=s), m).select("core", "est")
        out = e if out is None else out.unionByName(e)
    return out.groupBy("core").agg(F.round(F.avg("est"), 4).alias("est"))


def linear_fixed(df: DataFrame, m: int, k: int, n: int) -> DataFrame:
    """Bitmaps that are empty again at each block of k slots."""
    return linear_estimate(fixed_window(df, k, n), m, ("win",))


def linear_rebuild_sliding(df: DataFrame, m: int, k: int, n: int) -> DataFrame:
    """A new bitmap for every sliding window: the costly reference that recorders must equal."""
    return linear_estimate(expand_windows(df.select("core", "opp", "slot"), n, k), m, ("win",))
