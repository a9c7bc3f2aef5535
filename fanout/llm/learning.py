"""What the trained operators share: bounded labelled samples, held-out folds and logistic weights."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import stored, whole

THRESHOLD = 0.3


def fold(key: str | Column, folds: int) -> Column:
    """crc32 of the id as text, modulo the number of folds; a null id is in fold 0."""
    k = F.col(key) if isinstance(key, str) else key
    return F.crc32(F.coalesce(k.cast("string"), F.lit("")).cast("binary")) % folds


def sample_ids(labels: DataFrame, label: str, most: dict[int, int], keep: Column) -> DataFrame:
    """(doc_id, y) of at most most[v] rows with label v, those with the smallest hash of the id: at most sum(most) rows."""
    one = labels.filter(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & keep).groupBy("doc_id").agg(F.max(label).cast("int").alias("y"))
    parts = [one.filter(F.col("y") == v).orderBy(F.xxhash64("doc_id"), "doc_id").limit(n) for v, n in most.items()]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def sample_texts(docs: DataFrame, ids: DataFrame, most_bytes: int | None = None) -> DataFrame:
    """(doc_id, y) of a bounded sample -> (doc_id, y, t): one text for each id that documents has, of repeated ids the smallest.

    With `most_bytes` those of a class are taken by the hash of the id until that many bytes are reached; one at least.
    """
    texts = docs.select("doc_id", whole("text").alias("t")).join(F.broadcast(ids), "doc_id").groupBy("doc_id", "y").agg(F.min("t").alias("t"))
    if most_bytes is None:
        return texts
    texts, _ = stored(texts.withColumn("n", F.octet_length("t")).withColumn("o", F.xxhash64("doc_id")))
    used, kept = {}, []
    for r in sorted(texts.select("doc_id", "y", "n", "o").collect(), key=lambda r: (r["o"], r["doc_id"])):  # as many rows as the sample has
        if used.get(r["y"], 0) < most_bytes:
            kept.append((r["doc_id"],))
        used[r["y"]] = used.get(r["y"], 0) + r["n"]
    some = docs.sparkSession.createDataFrame(kept, texts.select("doc_id").schema)
    return texts.join(F.broadcast(some), "doc_id").select("doc_id", "y", "t")


def logistic(x: np.ndarray, y: np.ndarray, lasso: float = 0.0, rounds: int = 400) -> tuple[np.ndarray, float]:
    """Weights and intercept of a logistic model, by accelerated proximal steps; `lasso` is the L1 weight (0: a slight ridge)."""
    n, k = x.shape
    a = np.c_[x, np.ones(n)]
    step = 4.0 * n / (np.linalg.norm(a, 2) ** 2 + 1e-9)
    ridge = 0.0 if lasso else 1e-4
    w = np.zeros(k + 1)
    w[-1] = np.log((y.mean() + 1e-6) / (1 - y.mean() + 1e-6)) if n else 0.0
    v, t = w.copy(), 1.0
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(a @ v, -40, 40)))
        new = v - step * (a.T @ (p - y) / n + ridge * np.r_[v[:-1], 0])
        new[:-1] = np.sign(new[:-1]) * np.maximum(np.abs(new[:-1]) - step * lasso, 0)
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        v = new + (t - 1) / t2 * (new - w)
        w, t = new, t2
    return w[:-1], float(w[-1])


def shifted(margin: np.ndarray, y: np.ndarray, bias: float, at: float = THRESHOLD) -> float:
    """The intercept with which the cut of the best F1 on (margin without intercept, y) has the probability `at`."""
    order = np.argsort(-margin, kind="stable")
    hit = np.cumsum(y[order])
    f1 = 2 * hit / (np.arange(1, len(y) + 1) + y.sum())
    ends = np.r_[np.diff(margin[order]) != 0, True]  # a cut cannot part ties
    if not y.sum() or not ends.any():
        return bias
    k = int(np.flatnonzero(ends)[f1[ends].argmax()])
    s = margin[order]
    cut = (s[k] + s[k + 1]) / 2 if k + 1 < len(s) else s[k] - 1e-9
    return float(np.log(at / (1 - at)) - cut)
