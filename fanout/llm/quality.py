"""Quality by a sparse rule ensemble over text statistics, compiled into Spark column expressions.

Boosted shallow trees are grown on a bounded labelled sample; each path from a root is a rule, a conjunction of
comparisons. A lasso logistic model weighs the rules; those with a weight left become one column expression.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import whole
from .learning import THRESHOLD, fold, logistic, sample_ids, sample_texts, shifted

#: The bounded sample of labelled rows by class.
SAMPLE = {1: 12_000, 0: 6_000}
TREES, DEPTH, BINS, LASSO = 40, 3, 32, 0.002

STATISTICS = (
    "chars", "words", "word_length", "upper", "digit", "mark", "odd_mark", "bar", "lines", "line_length", "distinct_words", "distinct_lines", "stop_ends", "blank_lines",
)


def statistics(docs: DataFrame, text: str = "text") -> DataFrame:
    """documents -> all their columns and one column of doubles for each of STATISTICS, named _s_<name>; whole texts, null as empty."""
    t = whole(text)
    size, words, lines = F.length(t), F.split(F.trim(t), r"\s+"), F.split(t, "\n")
    gone = lambda pattern: size - F.length(F.regexp_replace(t, pattern, ""))
    dropped = lambda chars: size - F.length(F.translate(t, chars, ""))
    share = lambda n: n / F.greatest(size, F.lit(1))
    n_words, n_lines = F.size(words), F.size(lines)
    value = {
        "chars": F.log1p(size.cast("double")),
        "words": F.log1p(n_words.cast("double")),
        "word_length": size / n_words,
        "upper": share(gone(r"\p{Lu}+")),
        "digit": share(dropped("0123456789")),
        "mark": share(gone(r"[^\p{L}\p{N}\s]+")),
        "odd_mark": share(dropped("#$%&*<>{}[]\\^~_=+@")),
        "bar": share(dropped("|!")),
        "lines": F.log1p(n_lines.cast("double")),
        "line_length": F.log1p(size / n_lines),
        "distinct_words": F.size(F.array_distinct(words)) / n_words,
        "distinct_lines": F.size(F.array_distinct(lines)) / n_lines,
        "stop_ends": share(dropped(".")),
        "blank_lines": share(gone(r"\n\s*\n")),
    }
    return docs.withColumns({f"_s_{k}": v.cast("double") for k, v in value.items()})


@dataclass(frozen=True)
class Test:
    stat: int
    cut: float
    above: bool

    def holds(self, x: np.ndarray) -> np.ndarray:
        return (x[:, self.stat] > self.cut) == self.above

    def column(self) -> Column:
        c = F.col(f"_s_{STATISTICS[self.stat]}")
        return c > F.lit(self.cut) if self.above else c <= F.lit(self.cut)


Rule = frozenset  # of Test


def _tree(codes: np.ndarray, cuts: list[np.ndarray], g: np.ndarray, h: np.ndarray, rows: np.ndarray, path: tuple, depth: int, rules: list, value: np.ndarray, rate: float) -> None:
    """Grows one tree on gradients; notes every path in rules and adds leaf steps to value."""
    best = (1e-6, None)
    if depth and len(rows) >= 40:
        total_g, total_h = g[rows].sum(), h[rows].sum()
        base = total_g**2 / (total_h + 1)
        for f, cut in enumerate(cuts):
            if not len(cut):
                continue
            sg = np.cumsum(np.bincount(codes[rows, f], g[rows], len(cut) + 1))[:-1]
            sh = np.cumsum(np.bincount(codes[rows, f], h[rows], len(cut) + 1))[:-1]
            sn = np.cumsum(np.bincount(codes[rows, f], minlength=len(cut) + 1))[:-1]
            gain = np.where((sn >= 20) & (len(rows) - sn >= 20), sg**2 / (sh + 1) + (total_g - sg) ** 2 / (total_h - sh + 1) - base, 0)
            k = int(gain.argmax())
            if gain[k] > best[0]:
                best = (gain[k], (f, k))
    if best[1] is None:
        value[rows] += rate * -g[rows].sum() / (h[rows].sum() + 1)
        return
    f, k = best[1]
    left = codes[rows, f] <= k
    for side, above in ((rows[left], False), (rows[~left], True)):
        p = (*path, Test(f, float(cuts[f][k]), above))
        rules.append(Rule(p))
        _tree(codes, cuts, g, h, side, p, depth - 1, rules, value, rate)


def rules_of(x: np.ndarray, y: np.ndarray, trees: int = TREES, depth: int = DEPTH, bins: int = BINS) -> list[Rule]:
    """The different paths of boosted trees over the statistics x of shape (rows, statistics)."""
    cuts = [np.unique(np.quantile(c, np.linspace(0, 1, bins + 1)[1:-1])) for c in x.T]
    cuts = [(c[:-1] + c[1:]) / 2 if len(c) > 1 else c for c in cuts]
    codes = np.stack([np.searchsorted(c, v, side="left") for c, v in zip(cuts, x.T)], 1)
    value, rules, rng = np.full(len(y), np.log((y.mean() + 1e-6) / (1 - y.mean() + 1e-6))), [], np.random.default_rng(11)
    for _ in range(trees):
        p = 1 / (1 + np.exp(-value))
        rows = np.sort(rng.permutation(len(y))[: max(1, len(y) * 2 // 3)])
        step = np.zeros(len(y))
        found: list[Rule] = []
        _tree(codes, cuts, p - y, p * (1 - p), rows, (), depth, found, step, 0.3)
        for leaf in found:  # rows outside the tree's share move with the leaf they fall in
            rules.append(leaf)
        out = np.setdiff1d(np.arange(len(y)), rows)
        if len(out):
            step[out] = _leaf_steps(found, x, out, rows, step)
        value += step
    return list(dict.fromkeys(rules))


def _leaf_steps(found: list[Rule], x: np.ndarray, out: np.ndarray, rows: np.ndarray, step: np.ndarray) -> np.ndarray:
    """The steps of the longest rules that hold for the rows `out`, as the rows of the sample have them."""
    got = np.zeros(len(out))
    for r in sorted(found, key=len):
        inside = rows[np.logical_and.reduce([t.holds(x[rows]) for t in r])]
        if len(inside):
            got[np.logical_and.reduce([t.holds(x[out]) for t in r])] = step[inside[0]]
    return got


@dataclass
class Model:
    rules: list[Rule]
    weights: list[float]
    bias: float

    def column(self) -> Column:
        """The probability as an expression of the statistics columns."""
        margin = F.lit(self.bias)
        for r, w in zip(self.rules, self.weights):
            cond = None
            for t in sorted(r, key=lambda t: (t.stat, t.cut, t.above)):
                cond = t.column() if cond is None else cond & t.column()
            margin = margin + F.when(cond, F.lit(w)).otherwise(F.lit(0.0))
        return F.lit(1.0) / (F.lit(1.0) + F.exp(-F.least(F.greatest(margin, F.lit(-40.0)), F.lit(40.0))))


def fit(x: np.ndarray, y: np.ndarray, lasso: float = LASSO) -> Model:
    """Rules and their lasso weights; one class only: no rules and its share as every score."""
    if not len(y) or y.min() == y.max():
        return Model([], [], 40.0 if len(y) and y[0] else -40.0)
    rules = rules_of(x, y)
    z = np.stack([np.logical_and.reduce([t.holds(x) for t in r]) for r in rules], 1).astype(float) if rules else np.zeros((len(y), 0))
    w, bias = logistic(z, y.astype(float), lasso)
    keep = np.flatnonzero(np.abs(w) > 1e-4)
    return Model([rules[i] for i in keep], [float(w[i]) for i in keep], shifted(z[:, keep] @ w[keep], y, bias))


def fit_labelled(docs: DataFrame, labels: DataFrame, folds: int = 5, left_out: int = 0) -> Model:
    """The model of at most SAMPLE labelled rows outside the left-out fold; their statistics are all that the driver gets."""
    ids = sample_ids(labels, "quality", SAMPLE, fold("doc_id", folds) != left_out)
    cols = [f"_s_{s}" for s in STATISTICS]
    rows = statistics(sample_texts(docs, ids), "t").select("doc_id", "y", *cols).toPandas().sort_values(["doc_id", *cols])
    return fit(rows[cols].to_numpy(float), rows["y"].to_numpy(int))


def quality(docs: DataFrame, labels: DataFrame, folds: int = 5, left_out: int = 0, threshold: float = THRESHOLD) -> DataFrame:
    """documents, labels(doc_id, quality) -> doc_id, held_out, score, predicted for every row of documents, repeated ones each.

    Labels of the left-out fold are not looked at. Null labels are skipped, repeated ones count as their largest; of repeated
    doc_ids the smallest text is learned from. Null texts are empty, and empty texts have a score. Without labels of both classes all scores are equal. Empty input: no rows. Other
    columns are ignored. One map in built-in functions, without a shuffle.
    """
    model = fit_labelled(docs, labels, folds, left_out)
    return statistics(docs.select("doc_id", "text")).select("doc_id", (fold("doc_id", folds) == left_out).alias("held_out"), model.column().alias("score")).withColumn(
        "predicted", (F.col("score") >= threshold).cast("int")
    )
