"""Hashes of addresses and counterparts as column expressions; integers only, inside code generation."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .params import ADDRESS_BITS, GridParams

#: The prime, and multiplier and addend of either round for the root and the recorder hash.
PRIME = 2147483647
ROOT = (1103515245, 12345, 1566083941, 907633385)
RECORDER = (1496401, 11, 1812433253, 77)
POOL = (1220703125, 101, 1389796, 40692)
#: Multiplier of the key codec and its inverse modulo 2^32.
CODEC, CODEC_INVERSE = 1640531541, 263735037
LOW32 = 0xFFFFFFFF


def mixed(x: Column, consts: tuple[int, int, int, int]) -> Column:
    """Two affine rounds modulo the prime with a shift between; x below 2^32 keeps all products in 63 bits."""
    a1, b1, a2, b2 = consts
    h = (x.cast("long") * F.lit(a1) + F.lit(b1)) % F.lit(PRIME)
    return (h.bitwiseXOR(F.shiftright(h, 15)) * F.lit(a2) + F.lit(b2)) % F.lit(PRIME)


def salted(salt: int) -> tuple[int, int, int, int]:
    a1, b1, a2, b2 = RECORDER
    return a1 + 2 * salt, b1 + 977 * salt, a2, b2


def rec_hash(opp: Column, m: int, salt: int = 0) -> Column:
    """Recorder 0..m-1 of a counterpart."""
    return mixed(opp, salted(salt)) % F.lit(m)


def root_hash(core: Column, w: int) -> Column:
    return mixed(core, ROOT).bitwiseAND(F.lit((1 << w) - 1))


def grid_column(core: Column, row: int, p: GridParams) -> Column:
    """Column of an address in a row: row 0 is the root hash, the others hide a piece of the address in it."""
    root = root_hash(core, p.w)
    return root if row == 0 else F.shiftright(core, p.shift(row)).bitwiseXOR(root).bitwiseAND(F.lit(p.mask))


def grid_columns(core: Column, p: GridParams) -> Column:
    return F.array(*(grid_column(core, i, p) for i in range(p.r)))


def piece(column: Column, root: Column) -> Column:
    return column.bitwiseXOR(root)


def rebuild(cols: list[Column], p: GridParams) -> Column:
    """The address whose columns these are; with literal_shift its lowest d bits are 0."""
    out = None
    for i in range(1, p.r):
        part = F.shiftleft(piece(cols[i], cols[0]), p.shift(i))
        out = part if out is None else out.bitwiseOR(part)
    return out


def rebuild_literal(chains: DataFrame, p: GridParams) -> DataFrame:
    """Chains under literal_shift -> one row for each of the 2^d ends of the address whose root hash is the chain's."""
    high = chains.withColumn("_high", rebuild([F.col(f"c{i}") for i in range(p.r)], p)).filter(F.col("_high") < (1 << ADDRESS_BITS))
    return (
        high.withColumn("_low", F.explode(F.sequence(F.lit(0), F.lit((1 << p.d) - 1))))
        .withColumn("core", F.col("_high").bitwiseOR(F.col("_low").cast("long")))
        .filter(root_hash(F.col("core"), p.w) == F.col("c0"))
        .drop("_high", "_low")
    )


def encode_key(x: Column) -> Column:
    """A key below 2^32 spread over all 32 bits."""
    return (x.cast("long") * F.lit(CODEC)).bitwiseAND(F.lit(LOW32))


def decode_key(x: Column) -> Column:
    return (x * F.lit(CODEC_INVERSE)).bitwiseAND(F.lit(LOW32))


def key32(text: Column) -> Column:
    """The first 32 bits of the MD5 of a text."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long")


def ip_to_long(text: Column) -> Column:
    parts = F.split(text, r"\.")
    return sum((F.get(parts, i).cast("long") * F.lit(256 ** (3 - i)) for i in range(1, 4)), F.get(parts, 0).cast("long") * F.lit(256**3))


def long_to_ip(x: Column) -> Column:
    return F.concat_ws(".", *(F.shiftright(x, s).bitwiseAND(F.lit(255)).cast("string") for s in (24, 16, 8, 0)))


def hash_quality(cores: DataFrame, p: GridParams) -> DataFrame:
    """(core) -> for each row: cells used, heaviest and mean load, chi-square against an even spread. Repeated cores count once."""
    each = cores.select("core").distinct().select(F.posexplode(grid_columns(F.col("core"), p)).alias("row_id", "col_id"))
    load = each.groupBy("row_id", "col_id").agg(F.count("*").alias("n"))
    total = F.sum("n")
    even = total / F.lit(float(1 << p.w))
    return load.groupBy(F.col("row_id").cast("long").alias("row_id")).agg(
        F.count("*").alias("cells"),
        F.max("n").alias("max_load"),
        F.round(F.avg("n"), 6).alias("mean_load"),
        F.round(F.sum(F.col("n").cast("double") * F.col("n")) / even - total, 6).alias("chi_square"),
    )


def estimate(touched: Column, m: int) -> Column:
    """-m ln(free / m), with at least one recorder taken as free."""
    return F.round(-F.lit(float(m)) * F.log(F.greatest(F.lit(m) - touched, F.lit(1)).cast("double") / F.lit(float(m))), 6)
