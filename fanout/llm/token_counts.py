"""Token counts of whole texts, huge ones by overlapping chunks that are spliced where they agree.

The tokenizer drops white space before it splits words, so a text cut at white space has the tokens of its
two parts. A chunk's first and last word may be torn; the overlap of two chunks is searched for white
space at which both encodings have a boundary and after which both give the same tokens. If there is none,
the overlap is doubled, up to the rest of the text.

The library's own normaliser takes a fifth of the time. Where its rule is NFC, blanks and lower case, texts of characters
below `PLAIN` are normalised as a whole before, and the same tokenizer without normaliser encodes them.
"""

from __future__ import annotations

import json
import unicodedata
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import whole

CHUNK, OVERLAP, LIMIT = 65_536, 512, 2_048
#: Characters whose NFC and lower case all Unicode versions agree in; the rule that is known, as the tokenizer's file has it.
PLAIN = "\u0590"
NORMALISER = [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": "\\s+"}, "content": " "}, {"type": "Lowercase"}]
_LOADED: dict = {}
_BARE: dict = {}


def tokenizer(path: str):
    """The tokenizer of a file, loaded once in a process."""
    if path not in _LOADED:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        t = Tokenizer.from_file(path)
        t.no_truncation()
        t.no_padding()
        _LOADED[path] = t
    return _LOADED[path]


def bare_tokenizer(path: str):
    """(the same tokenizer without its normaliser, its added tokens in lower case); None where the rule is another or blanks are not dropped by the split."""
    if path not in _BARE:
        from tokenizers import Tokenizer

        tok = tokenizer(path)
        spec = json.loads(tok.to_str())
        split = ((spec["pre_tokenizer"] or {}).get("pretokenizers") or [{}])[0]
        _BARE[path] = None
        if (spec["normalizer"] or {}).get("normalizers") == NORMALISER and split.get("behavior") == "Removed" and split.get("invert") and split["pattern"].get("Regex", "").endswith("|[^\\s\\p{L}\\p{N}]+"):
            bare = Tokenizer.from_str(json.dumps(spec | {"normalizer": None}))
            _BARE[path] = bare, [x["content"].lower() for x in spec["added_tokens"]]
    return _BARE[path]


def normalised(text: str, added: list[str]) -> str | None:
    """What the normaliser makes of a text, but for the kind and number of its blanks; None where it is left to the library."""
    if not text.isascii():
        if max(text) >= PLAIN:
            return None
        text = unicodedata.normalize("NFC", text).replace("Σ", "σ")  # the library lowers each character by itself
    text = text.lower()
    return None if any(a in text for a in added) else text


def _encoded(tok, part: str, at: int) -> list[tuple[int, int, int]]:
    """(begin, end, id) of the tokens of a chunk that begins at `at`."""
    e = tok.encode(part, add_special_tokens=False)
    return [(a + at, b + at, i) for (a, b), i in zip(e.offsets, e.ids)]


def _meeting(text: str, left: list, right: list, low: int, high: int) -> int | None:
    """A place low < p < high at white space that both encodings respect, with equal tokens from it to the next such place; None if there is none."""
    spaces = [p for p in range(low + 1, high - 1) if text[p].isspace()]
    for p, q in zip(spaces, spaces[1:]):
        a, b = ([t for t in side if p <= t[0] < q] for side in (left, right))
        if a and a == b and not any(t[0] < p < t[1] or t[0] < q < t[1] for side in (left, right) for t in side):
            return p
    return None


def chunked_count(tok, text: str, chunk: int = CHUNK, overlap: int = OVERLAP) -> int:
    """Tokens of `text`, encoded in chunks of `chunk` characters; equal to the count of the whole text."""
    if len(text) <= chunk:
        return len(tok.encode(text, add_special_tokens=False).ids)
    total, start, end = 0, 0, chunk
    left, since = _encoded(tok, text[:end], 0), 0
    while end < len(text):
        lap = overlap
        while True:
            begin = max(since, end - lap)
            stop = min(len(text), begin + max(chunk, 2 * lap))
            right = _encoded(tok, text[begin:stop], begin)
            near = [t for t in left if t[1] >= begin]
            p = _meeting(text, near, [t for t in right if t[0] <= end], begin, end)
            if p is not None or begin == since:
                break
            lap *= 2
        if p is None:  # no common boundary since the last splice: the piece is encoded anew as one, longer
            end = min(len(text), since + 2 * (end - since))
            left = _encoded(tok, text[since:end], since)
            continue
        total += sum(t[0] < p for t in left)
        left, since, end = [t for t in right if t[0] >= p], p, stop
    return total + len(left)


def count_tokens(docs: DataFrame, path: str, limit: int = LIMIT, key: str = "doc_id", text: str = "text", chunk: int = CHUNK, overlap: int = OVERLAP) -> DataFrame:
    """documents -> doc_id, n_bytes, n_tokens, over_limit: one row per input row, in a map without a shuffle.

    Null and empty texts have no tokens. Repeated rows are counted each; other columns are ignored. Memory is
    bounded by one text and the tokens of one chunk, unless a text has no white space at all.
    """

    def counts(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        whole_rule, bare = tokenizer(path), bare_tokenizer(path)
        for b in batches:
            n, small, held = [0] * len(b), {}, 0

            def flush():
                nonlocal held
                for tok, some in small.values():
                    for (i, _), e in zip(some, tok.encode_batch_fast([t for _, t in some], add_special_tokens=False)):
                        n[i] = len(e)
                small.clear()
                held = 0

            for i, t in enumerate(b["_text"].tolist()):
                ready = normalised(t, bare[1]) if bare else None
                tok, t = (whole_rule, t) if ready is None else (bare[0], ready)
                if len(t) > chunk:
                    n[i] = chunked_count(tok, t, chunk, overlap)
                    continue
                small.setdefault(id(tok), (tok, []))[1].append((i, t))
                held += len(t)
                if held > 1 << 20:
                    flush()
            flush()
            yield pd.DataFrame({"doc_id": b["doc_id"], "n_bytes": b["n_bytes"], "n_tokens": n})

    base = docs.select(F.col(key).alias("doc_id"), whole(text).alias("_text")).select("doc_id", F.octet_length("_text").cast("long").alias("n_bytes"), "_text")
    kind = docs.schema[key].dataType.simpleString()
    out = base.mapInPandas(counts, f"doc_id {kind}, n_bytes long, n_tokens long")
    return out.withColumn("over_limit", F.col("n_tokens") > limit)
