"""The hashes and estimates as SQL functions of a session; their bodies are expressions, so plans stay inside code generation."""

from __future__ import annotations

from pyspark.sql import SparkSession

from .hashing import PRIME, RECORDER, ROOT


def _mixed(consts: tuple[int, int, int, int]) -> str:
    a1, b1, a2, b2 = consts
    h = f"((x * {a1} + {b1}) % {PRIME})"
    return f"(({h} ^ shiftright({h}, 15)) * {a2} + {b2}) % {PRIME}"


def register(spark: SparkSession) -> None:
    """Adds rec_hash(x, m), root_hash(x, w), hot_cutoff(m, theta) and fanout_estimate(touched, m) to the session."""
    for text in (
        f"rec_hash(x BIGINT, m INT) RETURNS BIGINT RETURN ({_mixed(RECORDER)}) % m",
        f"root_hash(x BIGINT, w INT) RETURNS BIGINT RETURN ({_mixed(ROOT)}) & (shiftleft(1L, w) - 1)",
        "hot_cutoff(m INT, theta INT) RETURNS DOUBLE RETURN m * (1 - exp(-theta / CAST(m AS DOUBLE)))",
        "fanout_estimate(touched BIGINT, m INT) RETURNS DOUBLE RETURN round(-CAST(m AS DOUBLE) * ln(CAST(greatest(m - touched, 1) AS DOUBLE) / m), 6)",
    ):
        spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION " + text)
