"""Accuracy, error, memory and work."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.params import GridParams
from ..sources.storage import stored


#: Rows of the truth that are sent to all tasks at most; beyond, both lists are joined by a shuffle.
TRUTH_SEND = 1_000_000


def accuracy(found: DataFrame, truth: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, core) of either, each once -> n_true, n_found, n_false, n_missed, fpr, fnr, tfr; rates are shares of the true ones, null without any.

    What was found can be far more than the truth and stays where it is: it is counted in place, with those that are true.
    """
    truth = stored(truth.select(*by, "core", F.lit(1).alias("_t")))
    found = found.select(*by, "core", F.lit(1).alias("_f"))
    if truth.count() <= TRUTH_SEND:
        met = found.join(F.broadcast(truth), [*by, "core"], "left").groupBy(*by).agg(F.count("*").alias("n_found"), F.count("_t").alias("_met"))
        true = truth.groupBy(*by).agg(F.count("*").alias("n_true"))
        n = (met.join(true, [*by], "full") if by else met.crossJoin(true)).fillna(0, ["n_found", "_met", "n_true"])
        n = n.select(*by, "n_true", "n_found", (F.col("n_found") - F.col("_met")).alias("n_false"), (F.col("n_true") - F.col("_met")).alias("n_missed"))
    else:
        n = truth.join(found, [*by, "core"], "full").groupBy(*by).agg(
            F.count("_t").alias("n_true"), F.count("_f").alias("n_found"), F.count_if(F.col("_t").isNull()).alias("n_false"), F.count_if(F.col("_f").isNull()).alias("n_missed")
        )
    rate = lambda c: F.when(F.col("n_true") > 0, F.round(c / F.col("n_true"), 6))
    return n.withColumns({"fpr": rate(F.col("n_false")), "fnr": rate(F.col("n_missed")), "tfr": rate(F.col("n_false") + F.col("n_missed"))})


def accuracy_summary(scores: DataFrame, by: str = "detector") -> DataFrame:
    """Mean rates over windows."""
    return scores.groupBy(by).agg(F.count("*").alias("windows"), *(F.round(F.avg(c), 6).alias(f"mean_{c}") for c in ("fpr", "fnr", "tfr")))


def accuracy_series(scores: DataFrame) -> DataFrame:
    """Mean rates, and the share of windows with FPR below 2 %."""
    return scores.agg(
        F.count("*").alias("windows"), *(F.round(F.avg(c), 6).alias(f"mean_{c}") for c in ("fpr", "fnr", "tfr")),
        F.round(F.avg(F.when(F.col("fpr").isNotNull(), (F.col("fpr") < 0.02).cast("double"))), 6).alias("low_fpr_share"),
    )


def fpr_fnr_corr(scores: DataFrame) -> DataFrame:
    """Correlation of both rates over windows; null where one of them does not vary."""
    n = scores.filter("fpr is not null and fnr is not null").agg(F.covar_samp("fpr", "fnr").alias("c"), F.stddev("fpr").alias("a"), F.stddev("fnr").alias("b"))
    return n.select(F.when((F.col("a") > 0) & (F.col("b") > 0), F.round(F.try_divide("c", F.col("a") * F.col("b")), 4)).alias("corr"))


def estimate_error(estimates: DataFrame, truth: DataFrame) -> DataFrame:
    """(core, est) beside (core, fan_out): mean and root mean square relative error, and bias."""
    e = estimates.select("core", "est").join(truth, "core")
    rel = (F.col("est") - F.col("fan_out")) / F.col("fan_out")
    return e.agg(
        F.count("*").alias("cores"), F.round(F.avg(F.abs(rel)), 6).alias("mean_error"), F.round(F.sqrt(F.avg(rel * rel)), 6).alias("rms_error"),
        F.round(F.avg(F.col("est") - F.col("fan_out")), 4).alias("bias"),
    )


def error_by_load(estimates: DataFrame, truth: DataFrame, m: int) -> DataFrame:
    """Errors by load n/m in eighths, beside the standard error that theory gives for the mean load of the class."""
    e = estimates.select("core", "est").join(truth, "core").withColumn("load", F.floor(F.col("fan_out") * 8 / m))
    rel = (F.col("est") - F.col("fan_out")) / F.col("fan_out")
    out = e.groupBy("load").agg(F.count("*").alias("cores"), F.round(F.sqrt(F.avg(rel * rel)), 6).alias("rms_error"), F.avg("fan_out").alias("n"))
    t = F.col("n") / m
    return out.withColumn("theory", F.round(F.sqrt(F.lit(float(m)) * (F.exp(t) - t - 1)) / F.col("n"), 6)).drop("n")


def work_counters(contacts: DataFrame, hot: DataFrame, chains: DataFrame, p: GridParams) -> DataFrame:
    """One row: contacts, recorder writes, tests that a plain product of the first three rows takes, and chains by level."""
    per_row = hot.groupBy().agg(*(F.count_if(F.col("row_id") == i).alias(f"h{i}") for i in range(3)))
    levels = chains.groupBy().agg(*(F.coalesce(F.max(F.when(F.col("level") == i, F.col("chains"))), F.lit(0)).alias(f"chains_{i}") for i in range(2, p.r)))
    n = contacts.agg(F.count("*").alias("contacts"))
    return n.crossJoin(per_row).crossJoin(levels).select(
        "contacts", (F.col("contacts") * p.r).alias("writes"), (F.col("h0") * F.col("h1") * F.col("h2")).alias("start_tests"), *(f"chains_{i}" for i in range(2, p.r))
    )


def throughput(contacts: int, seconds: float, packet_bytes: int = 800) -> dict[str, float]:
    """Contacts a second, and the bit rate they would be at so many bytes a packet: by the published formula (millions a second
    times bits, over 1,024, so that 109 million are 681.25) and in Gb/s of 10^9."""
    rate = contacts / seconds
    return {"contacts_s": rate, "published_gb_s": rate / 1e6 * packet_bytes * 8 / 1024, "gb_s": rate * packet_bytes * 8 / 1e9}


def top_heavy(heavy: DataFrame, n: int, by: tuple[str, ...] = ()) -> DataFrame:
    """The n widest fan-outs, for each value of by if there is one; ties go to the smaller address."""
    if not by:
        return heavy.orderBy(F.desc("fan_out"), "core").limit(n)
    w = Window.partitionBy(*by).orderBy(F.desc("fan_out"), "core")
    return heavy.withColumn("nth", F.row_number().over(w).cast("long")).filter(F.col("nth") <= n)
