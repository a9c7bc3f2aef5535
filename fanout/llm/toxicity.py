"""Toxicity by compression distance: zstandard dictionaries of toxic and of ordinary text.

A text is cut at blanks into windows. Each is compressed with either dictionary; how many bytes the toxic one saves over
the ordinary one is the window's distance. The ordinary dictionary is trained on windows of ordinary text and, so that its
commonest words are sure to be there, on excerpts of it; the toxic one is trained on excerpts of toxic text and ends in the
ordinary one, at the same offsets, so that windows without anything toxic are equally long under both. An excerpt is what is
left of a text, in its order, when words are left out that are not typical of its class. Words count as typical only if they
are met after many different words; those of a passage that is merely copied often have few such contexts.
The contents of the trained dictionaries are loaded without their entropy tables, which are tuned to long samples and blur
the lengths of short windows.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import whole
from .learning import THRESHOLD, fold, logistic, sample_ids, sample_texts, shifted

WINDOW, OWN_BYTES, COMMON_BYTES = 64, 4_096, 32_768
#: The bounded sample: labelled rows by class with their whole texts, and bytes of text by class; then the windows, chosen at
#: random from all its ordinary texts, that the ordinary dictionary is trained on.
SAMPLE, SAMPLE_BYTES, PLAIN_WINDOWS = {1: 3_000, 0: 7_000}, 48 << 20, 40_000
TYPICAL, CONTEXTS = 1.5, 0.8


def windows(text: str, size: int = WINDOW) -> list[bytes]:
    """The whole text in lower case as windows of at most `size` bytes, cut at blanks where there is one; each begins and ends with a blank if it can."""
    b = b" " + b" ".join(text.lower().encode().split()) + b" "
    out, i, last = [], 0, len(b) - 1
    while i < last:
        j = i + size
        if j < last:
            k = b.rfind(b" ", i + 1, j)
            j = k if k > 0 else j
        out.append(b[i : j + 1])
        i = j
    return out


def _settings():
    import zstandard as z

    return z.ZstdCompressionParameters(
        compression_level=3, strategy=z.STRATEGY_BTLAZY2, min_match=5, window_log=18, hash_log=17, chain_log=17, search_log=4, target_length=8,
        write_content_size=False, write_checksum=False, write_dict_id=False,
    )


def compressor(content: bytes):
    import zstandard as z

    p, d = _settings(), z.ZstdCompressionDict(content, dict_type=z.DICT_TYPE_RAWCONTENT)
    d.precompute_compress(compression_params=p)
    return z.ZstdCompressor(dict_data=d, compression_params=p)


def _loads(dictionary: bytes) -> bool:
    import zstandard as z

    try:
        d = z.ZstdCompressionDict(dictionary, dict_type=z.DICT_TYPE_FULLDICT)
        d.precompute_compress(compression_params=_settings())
        z.ZstdCompressor(dict_data=d, compression_params=_settings()).compress(b" ")
        return True
    except z.ZstdError:
        return False


def content(dictionary: bytes) -> bytes:
    """What follows the entropy tables of a trained dictionary: the shortest beginning that loads has 8 bytes of it; empty where there is less."""
    for n in range(9, min(len(dictionary), 4_096)):
        if _loads(dictionary[:n]):
            return dictionary[n - 8 :]
    return b""


def _trained(samples: list[bytes], size: int, **how) -> bytes:
    """The content of a dictionary trained on the samples, at most `size` bytes; the samples themselves, cut to the size, where they are too few to train on."""
    import zstandard as z

    try:
        trained = content(z.train_dictionary(size + 512, samples, **how).as_bytes())[-size:]
    except z.ZstdError:
        trained = b""
    return trained or b"".join(samples)[:size]


def excerpts(texts: list[str], words: list[bytes]) -> list[bytes]:
    """Windows over what is left of each text when only these words stay, in their order."""
    some = set(words)
    left = (b" ".join(w for w in t.lower().encode().split() if w in some).decode() for t in texts)
    return [w for t in left for w in windows(t)]


def _typical(texts: dict[int, list[str]]) -> dict[int, list[bytes]]:
    """For each class the words that are typical of it, those with the most contexts first.

    Toxic: the log odds less two standard errors are above TYPICAL. Ordinary: the odds lean to it. Either way the words
    before it must be nearly as many as the texts that have it, which those of a copied passage are not.
    """
    seen: dict[int, Counter] = {0: Counter(), 1: Counter()}
    for y, ts in texts.items():
        for t in ts:
            seen[y].update(set(t.lower().encode().split()))
    n1, n0 = len(texts[1]) + 1, len(texts[0]) + 1

    def odds(w: bytes) -> tuple[float, float]:
        a, b = seen[1][w] + 0.5, seen[0][w] + 0.5
        return float(np.log(a / n1) - np.log(b / n0)), float(np.sqrt(1 / a + 1 / b))

    def fits(w: bytes, y: int) -> bool:
        o, e = odds(w)
        return o - 2 * e > TYPICAL if y else o < 0

    out = {}
    for y in (1, 0):  # only words that can be chosen have their contexts gathered: a few of all that there are
        before = {w: set() for w, n in seen[y].items() if n >= 3 and fits(w, y)}
        for t in texts[y]:
            last = b""
            for w in t.lower().encode().split():
                if w in before:
                    before[w].add(last)
                last = w
        ws = [w for w, c in before.items() if len(c) >= 3 and len(c) >= CONTEXTS * seen[y][w]]
        out[y] = sorted(ws, key=lambda w: (-len(before[w]), w))
    out[0] = out[0][: 2 * max(50, len(out[1]))]
    return out


class Model:
    """Two dictionaries and the weights that turn a text's window distances into a probability."""

    def __init__(self, toxic: bytes, ordinary: bytes, weights: np.ndarray, bias: float):
        self.toxic, self.ordinary, self.weights, self.bias, self.ready = toxic, ordinary, weights, bias, None

    def __getstate__(self):
        return self.__dict__ | {"ready": None}

    def features(self, text: str) -> list[float]:
        if self.ready is None:
            self.ready = compressor(self.toxic), compressor(self.ordinary)
        t, o = self.ready[0].compress, self.ready[1].compress
        d = np.array([len(o(w)) - len(t(w)) for w in windows(text)] or [0])
        saved = np.maximum(d, 0)
        return [float(saved.mean()), min(12, int(d.max())) / 4, float(np.log1p((d >= 4).sum())), float((d >= 4).mean()) * 4, float(np.log1p((d >= 6).sum()))]

    def score(self, text: str) -> float:
        m = float(np.dot(self.features(text), self.weights)) + self.bias
        return 1 / (1 + np.exp(-max(-40.0, min(40.0, m))))


def fit(texts: list[str], toxic: list[int]) -> Model:
    """Dictionaries from two thirds of the samples, weights and threshold from the rest; one class only: its share is every score."""
    y = np.array(toxic, np.int64)
    if not len(y) or y.min() == y.max():
        return Model(b" " * 16, b" " * 16, np.zeros(5), 40.0 if len(y) and y[0] else -40.0)
    own_half = np.zeros(len(y), bool)  # two thirds train the dictionaries, the rest the weights
    for k in (0, 1):
        own_half[y == k] = np.arange((y == k).sum()) % 3 < 2
    train = {k: [texts[i] for i in np.flatnonzero(own_half & (y == k))] for k in (0, 1)}
    rng = np.random.default_rng(7)
    plain = [w for t in train[0] for w in windows(t)]
    common = _trained([plain[i] for i in rng.permutation(len(plain))[:PLAIN_WINDOWS]], COMMON_BYTES)
    own = {}
    for k, ws in _typical(train).items():
        parts = excerpts(train[k], ws)
        own[k] = _trained([parts[i] for i in rng.permutation(len(parts))[:PLAIN_WINDOWS]], OWN_BYTES, k=32, d=6)
    ordinary = own[0] + common
    model = Model(own[1] + ordinary, b" " * len(own[1]) + ordinary, np.zeros(5), 0.0)
    rest = np.flatnonzero(~own_half)
    x = np.array([model.features(texts[i]) for i in rest])
    model.weights, bias = logistic(x, y[rest])
    model.bias = shifted(x @ model.weights, y[rest], bias)
    return model


def fit_labelled(docs: DataFrame, labels: DataFrame, folds: int = 4, left_out: int = 2) -> Model:
    """The model of at most SAMPLE labelled rows outside the left-out fold; the sample, of bounded bytes, is all that the driver gets."""
    rows = sample_texts(docs, sample_ids(labels, "toxic", SAMPLE, fold("doc_id", folds) != left_out), SAMPLE_BYTES).toPandas()
    rows = rows.sort_values(["doc_id", "t"])
    texts, toxic = rows["t"].tolist(), rows["y"].tolist()
    del rows
    return fit(texts, toxic)


def scores(spark: SparkSession, model: Model, text: str = "text") -> Column:
    """The score of the whole text as a column; null texts are empty, and score what an empty text does. A map without a shuffle."""
    from pyspark.sql.functions import pandas_udf

    sent = spark.sparkContext.broadcast(model)  # two dictionaries of fixed size and five weights

    @pandas_udf("double")
    def of(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        m = sent.value
        for b in batches:
            yield b.map(m.score)

    return of(whole(text))


def toxicity(docs: DataFrame, labels: DataFrame, folds: int = 4, left_out: int = 2, threshold: float = THRESHOLD) -> DataFrame:
    """documents, labels(doc_id, toxic) -> doc_id, held_out, score, predicted for every row of documents, repeated ones each.

    Labels of the left-out fold are not looked at. Null labels are skipped, repeated ones count as their largest; of repeated
    doc_ids the smallest text is learned from. Without labels of both classes all scores are equal. Empty input: no rows. Other
    columns are ignored. Very long texts are scored whole, window by window.
    """
    scored = docs.select("doc_id", scores(docs.sparkSession, fit_labelled(docs, labels, folds, left_out)).alias("score"))
    return scored.select("doc_id", (fold("doc_id", folds) == left_out).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
