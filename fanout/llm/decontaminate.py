"""Benchmark decontamination: n-gram seeds join passages to test items, Smith-Waterman alignment scores them.

The test items are the query set. They are taken in blocks of a bounded number of words, so that what is sent to the
tasks has a fixed bound however large the benchmark is; each block goes against all documents in one map. No seed is
set aside for being frequent: a leak may have only frequent ones. What they cost is kept down by a bound instead, as an
alignment scores no more than the words that item and passage share; places under the needed score are not aligned.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import whole

SEED_WORDS, BLOCK_WORDS = 3, 400_000
#: An alignment counts a word found +1, a word changed, missing or added -1.
NEEDED, NEEDED_SHARE = 12, 0.6
_WORD = re.compile(r"\w+")


def words_of(text: str) -> list[str]:
    return _WORD.findall(text.lower())


class Items:
    """A block of test items as word numbers (from 1; 0: any other word) and their seeds as sorted codes."""

    def __init__(self, rows: list[tuple[int, str]], n: int = SEED_WORDS):
        split = [(i, words_of(t)) for i, t in rows]
        self.vocabulary = {w: k for k, w in enumerate(dict.fromkeys(w for _, ws in split for w in ws), 1)}
        self.base, self.n = len(self.vocabulary) + 1, n
        self.ids = [i for i, _ in split]
        self.words = [np.array([self.vocabulary[w] for w in ws], np.int64) for _, ws in split]
        where = [(int(c), k, p) for k, ws in enumerate(self.words) for p, c in enumerate(self.codes(ws))]
        self.table = np.array(sorted(where) or np.zeros((0, 3)), np.int64).reshape(-1, 3)
        self.seeds = np.unique(self.table[:, 0])

    def codes(self, ws: np.ndarray) -> np.ndarray:
        """Codes of the n-grams of word numbers, modulo 2^62; -1 where one of the words is in no item. Like codes of unlike n-grams only cost an alignment."""
        m = len(ws) - self.n + 1
        if m <= 0:
            return np.zeros(0, np.int64)
        out, known = np.zeros(m, np.int64), np.ones(m, bool)
        for k in range(self.n):
            out = (out * self.base + ws[k : k + m]) & ((1 << 62) - 1)
            known &= ws[k : k + m] > 0
        return np.where(known, out, -1)

    def of(self, text: str) -> np.ndarray:
        get = self.vocabulary.get
        return np.array([get(w, 0) for w in words_of(text)], np.int64)

    def found(self, ws: np.ndarray, seeds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Places in ws at which one of the sorted seeds begins, and which."""
        codes = self.codes(ws)
        at = np.flatnonzero(codes >= 0)
        if not len(at) or not len(seeds):
            return at[:0], at[:0]
        k = np.minimum(np.searchsorted(seeds, codes[at]), len(seeds) - 1)
        hit = seeds[k] == codes[at]
        return at[hit], k[hit]


def align(item: np.ndarray, part: np.ndarray) -> tuple[int, int]:
    """Smith-Waterman over words: the best local score of an item in a part of a text, and where in the part it ends (exclusive)."""
    j = np.arange(len(part) + 1)
    row, best, end = np.zeros(len(part) + 1, np.int64), 0, 0
    for w in item:
        new = np.zeros_like(row)
        new[1:] = np.maximum(row[:-1] + np.where(part == w, 1, -1), row[1:] - 1)
        np.maximum(new, 0, out=new)
        row = np.maximum.accumulate(new + j) - j  # a word added costs 1 for each step to the right
        k = int(row.argmax())
        if row[k] > best:
            best, end = int(row[k]), k
    return best, end


def needed(length: int) -> int:
    """The score from which an item of so many words counts as leaked: 12, or 0.6 of a shorter one."""
    return min(NEEDED, max(1, int(np.ceil(NEEDED_SHARE * length))))


def shared_words(item: np.ndarray, part: np.ndarray) -> int:
    """Words of an item that a part of a text has, with repeats: no alignment of the two scores more."""
    kinds, n = np.unique(item, return_counts=True)
    k = np.minimum(np.searchsorted(kinds, part), len(kinds) - 1)
    return int(np.minimum(np.bincount(k[kinds[k] == part], minlength=len(kinds)), n).sum())


def leaks(docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", text: str = "text", block_words: int = BLOCK_WORDS) -> DataFrame:
    """documents, benchmark(item_id, text) -> doc_id, item_id, score, share, last_word: an item that aligns with a passage of a document.

    score: words aligned less edits; share: of the item's words; last_word: where in the document's words it ends. One row
    for each (document, item), repeated rows of documents each; a document that holds an item more than once gives its
    best place. Items shorter than a seed are only found as they are, through their whole word sequence. Null texts are
    empty; empty texts and items without words give nothing. Rows without a doc_id and items without an item_id are compared like
    others and come out with a null. Repeated items come out each. Other columns are ignored. No limit on items or places for a document.
    """
    spark, kind = docs.sparkSession, docs.schema[key].dataType.simpleString()
    kinds = f"doc_id {kind}, item_id {benchmark.schema['item_id'].dataType.simpleString()}, score long, share double, last_word long"
    corpus = docs.select(F.col(key).alias("doc_id"), whole(text).alias("_text"))
    blocks, held, size = [], [], 0
    for r in benchmark.select("item_id", whole("text").alias("text")).toLocalIterator():  # one block at a time is on the driver
        held.append((r["item_id"], r["text"]))
        size += len(words_of(r["text"]))
        if size >= block_words:
            blocks.append(_block_leaks(corpus, held, kinds))
            held, size = [], 0
    if held:
        blocks.append(_block_leaks(corpus, held, kinds))
    return reduce(DataFrame.unionByName, blocks) if blocks else spark.createDataFrame([], kinds)


def _block_leaks(corpus: DataFrame, rows: list[tuple[int, str]], kinds: str) -> DataFrame:
    spark = corpus.sparkSession
    rows = [r for r in rows if words_of(r[1])]
    kept = [Items([r for r in rows if len(words_of(r[1])) >= SEED_WORDS])]
    kept += [Items(s, n) for n in range(1, SEED_WORDS) if (s := [r for r in rows if len(words_of(r[1])) == n])]
    query = spark.sparkContext.broadcast([(s, s.seeds) for s in kept])

    def aligned(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            out = []
            for doc_id, t in zip(b["doc_id"].tolist(), b["_text"]):
                for items, seeds in query.value:
                    out += ((doc_id, *x) for x in matches(items, seeds, t))
            if out:
                yield pd.DataFrame(out, columns=["doc_id", "item_id", "score", "share", "last_word"])

    return corpus.mapInPandas(aligned, kinds)


def matches(items: Items, seeds: np.ndarray, text: str) -> list[tuple]:
    """(item_id, score, share, last word) of the items that leak into a text."""
    ws = items.of(text)
    at, k = items.found(ws, seeds)
    if not len(at):
        return []
    low = np.searchsorted(items.table[:, 0], seeds[k])
    high = np.searchsorted(items.table[:, 0], seeds[k], side="right")
    spots: dict[int, list[tuple[int, int]]] = {}
    for p, a, b in zip(at.tolist(), low.tolist(), high.tolist()):
        for _, item, off in items.table[a:b].tolist():
            n = len(items.words[item])
            slack = n // 3 + 2
            spots.setdefault(item, []).append((max(0, p - off - slack), min(len(ws), p - off + n + slack)))
    out = []
    for item, spans in spots.items():
        target, need, best, last = items.words[item], needed(len(items.words[item])), 0, 0
        spans.sort()
        merged = [list(spans[0])]
        for a, b in spans[1:]:
            if a <= merged[-1][1]:
                merged[-1][1] = max(b, merged[-1][1])
            else:
                merged.append([a, b])
        for a, b in merged:
            part = ws[a:b]
            if (shared := shared_words(target, part)) >= need and shared > best:  # it may beat the best so far
                score, end = align(target, part)
                if score > best:
                    best, last = score, a + end
        if best >= need:
            out.append((items.ids[item], best, best / len(target), last))
    return out
