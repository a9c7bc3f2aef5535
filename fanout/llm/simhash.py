"""Near-duplicates by SimHash fingerprints, with a byte-position inverted index and count filtering.

Fingerprints that differ in at most 3 of 64 bits differ in at most 3 of 8 bytes, so they share 5 positional bytes or
more, and of two halves of 4 bytes one shares 3. A posting list holds the fingerprints with the same 3 bytes at the
same 3 places of one half: 8 lists for each fingerprint. A list longer than `hot` is dealt anew by 2 of the other 5
bytes, as 5 have to be shared in all; what is left of the fingerprint has 24 bits, so such a list has a fixed bound.
In each list the shared bytes of a pair are tallied, pairs below 5 are left out, and the rest are verified by their
bits. A list gives only the edges of a spanning forest, never all its pairs.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import dropped, looked_up, stored, whole

BITS, SEED, HOT = 3, 42, 4_096


def fingerprint(text: str, shingle: int = 3, seed: int = SEED) -> int:
    """SimHash of a text: A-Z in lower case, words between white space, shingles with repeats; 0 without words."""
    import xxhash

    words = text.encode().lower().split()
    if not words:
        return 0
    n = max(1, len(words) - shingle + 1)
    flat = b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words]) - 1
    starts = [0, *(ends[: n - 1] + 1).tolist()]
    stops = ends[min(shingle, len(words)) - 1 :].tolist()
    h, ones = xxhash.xxh64_intdigest, np.zeros(64, np.int64)
    for at in range(0, n, 1 << 16):  # bounded memory for very long texts
        v = np.array([h(flat[a:b], seed) for a, b in zip(starts[at : at + (1 << 16)], stops[at : at + (1 << 16)])], dtype=">u8")
        ones += np.unpackbits(v.view(np.uint8)).reshape(-1, 64).sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(ones * 2 > n).tobytes(), "big")


def fingerprints(docs: DataFrame, shingle: int = 3, seed: int = SEED, key: str = "doc_id", text: str = "text") -> DataFrame:
    """documents -> doc_id, fp (the 64 bits as a signed long). Null texts are empty. A map without a shuffle."""

    def of(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield pd.DataFrame({"doc_id": b["doc_id"], "fp": np.array([fingerprint(t, shingle, seed) for t in b["_text"]], dtype=np.uint64).view(np.int64)})

    kind = docs.schema[key].dataType.simpleString()
    return docs.select(F.col(key).alias("doc_id"), whole(text).alias("_text")).mapInPandas(of, f"doc_id {kind}, fp long")


def _byte(pos: int):
    return F.shiftrightunsigned("fp", 8 * (7 - pos)).bitwiseAND(255)


def _list_key(tag: int, places: tuple[int, ...]):
    """A number for (tag, places, bytes there): at most 5 bytes and a tag below 2^16."""
    out = F.lit(tag).cast("long")
    for p in places:
        out = F.shiftleft(out, 8).bitwiseOR(_byte(p))
    return out


HALVES = [h for half in ((0, 1, 2, 3), (4, 5, 6, 7)) for h in combinations(half, 3)]


def forest(fp: np.ndarray, bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """Edges (indexes) that connect what pairs of `fp` (uint64, distinct) within `bits` bits connect."""
    n = len(fp)
    label = np.arange(n)
    out_a, out_b = [], []

    def find(i: int) -> int:
        while label[i] != i:
            label[i] = label[label[i]]
            i = label[i]
        return i

    for i in range(n - 1):
        x = fp[i + 1 :] ^ fp[i]
        shared = (x.view(np.uint8).reshape(-1, 8) == 0).sum(1)
        near = np.flatnonzero(shared >= 8 - bits)
        for j in near[np.bitwise_count(x[near]) <= bits] + i + 1:
            a, b = find(i), find(j)
            if a != b:
                label[max(a, b)] = min(a, b)
                out_a.append(i)
                out_b.append(j)
    return np.array(out_a, np.int64), np.array(out_b, np.int64)


def probed_forest(fp: np.ndarray, bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """As `forest` for a long list whose members share 5 bytes: its sorted members are probed with all flips of the bits that vary."""
    vary = int(np.bitwise_or.reduce(fp ^ fp[0]))
    places = [i for i in range(64) if vary >> i & 1]
    a, b = [], []
    for k in range(1, bits + 1):
        for c in combinations(places, k):
            other = fp ^ np.uint64(sum(1 << i for i in c))
            at = np.searchsorted(fp, other)
            hit = np.flatnonzero((at < len(fp)) & (fp[np.minimum(at, len(fp) - 1)] == other) & (other > fp))
            a.append(hit)
            b.append(at[hit])
    return np.concatenate(a), np.concatenate(b)


def links(fps: DataFrame, bits: int = BITS, hot: int = HOT) -> DataFrame:
    """fps(fp long, distinct) -> edges (a, b), a < b as fingerprints, that connect exactly what links of `bits` bits connect.

    Up to 3 bits. Works on posting lists that meet in one task sorted by key; singletons are dropped before that.
    """
    lists = fps.select("fp", F.posexplode(F.array(*(_list_key(i, h) for i, h in enumerate(HALVES)))).alias("half", "list"))
    sizes, sizes_path = stored(lists.groupBy("list").agg(F.count("*").alias("n")).filter("n > 1"))
    met = lists.join(sizes, "list")
    apart = met.filter(F.col("n") <= hot).select("list", "fp")
    more = []
    for i, h in enumerate(HALVES):
        rest = [p for p in range(8) if p not in h]
        more.append(F.array(*(_list_key(64 + 16 * i + j, h + c) for j, c in enumerate(combinations(rest, 2)))))
    deep = met.filter(F.col("n") > hot).select("fp", F.explode(F.element_at(F.array(*more), F.col("half") + 1)).alias("list")).select("list", "fp")
    dealt = apart.unionByName(deep).repartition("list").sortWithinPartitions("list", "fp")

    def pairs(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held_l, held_f = np.zeros(0, np.int64), np.zeros(0, np.int64)

        def out(key: np.ndarray, signed: np.ndarray) -> Iterator[pd.DataFrame]:
            cuts = np.flatnonzero(np.diff(key)) + 1
            starts, stops = np.r_[0, cuts], np.r_[cuts, len(key)]
            length = stops - starts
            fp = signed.view(np.uint64)
            got: list[tuple[np.ndarray, np.ndarray]] = []
            small = np.repeat(length <= 64, length)
            for lag in range(1, min(64, int(length.max(initial=1)))):
                i = np.flatnonzero(small[lag:] & (key[lag:] == key[:-lag]))
                if not len(i):
                    break
                x = fp[i] ^ fp[i + lag]
                i = i[(x.view(np.uint8).reshape(-1, 8) == 0).sum(1) >= 8 - bits]
                i = i[np.bitwise_count(fp[i] ^ fp[i + lag]) <= bits]
                got.append((i, i + lag))
            for s, e in zip(starts[length > 64], stops[length > 64]):
                own = np.sort(fp[s:e])
                a, b = (forest if e - s <= hot else probed_forest)(own, bits)
                yield frame(own[a], own[b])
            if got:
                yield frame(fp[np.concatenate([x for x, _ in got])], fp[np.concatenate([y for _, y in got])])

        def frame(a: np.ndarray, b: np.ndarray) -> pd.DataFrame:
            a, b = a.view(np.int64), b.view(np.int64)
            return pd.DataFrame({"a": np.minimum(a, b), "b": np.maximum(a, b)})

        for batch in batches:
            held_l, held_f = np.r_[held_l, batch["list"].to_numpy()], np.r_[held_f, batch["fp"].to_numpy()]
            last = int(np.searchsorted(held_l, held_l[-1]))
            if last:
                yield from out(held_l[:last], held_f[:last])
                held_l, held_f = held_l[last:], held_f[last:]
        if len(held_l):
            yield from out(held_l, held_f)

    found, _ = stored(dealt.mapInPandas(pairs, "a long, b long").distinct())
    dropped(fps.sparkSession, sizes_path)
    return found


def components(edges: DataFrame) -> DataFrame:
    """edges(a, b), a != b -> (node, root): the smallest node of each component, for nodes with an edge.

    Rounds of large-star and small-star; each stores its edges, so lineage stays short. Stops when a round changes nothing.
    """
    spark = edges.sparkSession
    kind = edges.schema["a"].dataType
    now, path = stored(edges.select(F.greatest("a", "b").alias("v"), F.least("a", "b").alias("u")).distinct())
    print_of = lambda df: df.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    mark = print_of(now)
    while mark[0]:
        both = now.union(now.select("u", "v")).toDF("x", "y")
        low = both.groupBy("x").agg(F.least(F.min("y"), F.col("x")).alias("m"))
        large = both.join(low, "x").filter("y > x").select(F.col("y").alias("v"), F.col("m").alias("u")).filter("v != u").distinct()
        low = large.groupBy("v").agg(F.min("u").alias("m"))
        linked = large.join(low, "v")
        small = linked.filter("u != m").select(F.col("u").alias("v"), F.col("m").alias("u")).union(low.select("v", F.col("m").alias("u")))
        new, new_path = stored(small.filter("v != u").distinct())
        dropped(spark, path)
        now, path, before = new, new_path, mark
        mark = print_of(now)
        if mark == before:
            break
    return now.select(F.col("v").cast(kind).alias("node"), F.col("u").alias("root")).union(now.select(F.col("u").cast(kind).alias("node"), F.col("u").alias("root")).distinct())


def near_duplicates(docs: DataFrame, shingle: int = 3, bits: int = BITS, seed: int = SEED, hot: int = HOT, key: str = "doc_id", text: str = "text") -> DataFrame:
    """documents -> doc_id, fingerprint (16 hex digits), component_id: the smallest doc_id reachable over links of at most `bits` bits.

    Texts without words, null ones included, have fingerprint 0 and are linked like any other. Repeated rows come out
    each. A null doc_id takes part, but is never a component_id unless its component has no other. Empty input: no rows.
    Equal fingerprints are combined before any link is sought. Other columns are ignored.
    """
    if not 0 <= bits <= 3:
        raise ValueError("the index is exact for 0 to 3 bits")
    fps, _ = stored(fingerprints(docs, shingle, seed, key, text))
    kinds, kinds_path = stored(fps.groupBy("fp").agg(F.min("doc_id").alias("first"), F.count("*").alias("copies")))
    edges = links(kinds.select("fp"), bits, hot)
    merged = kinds.join(components(edges), F.col("fp") == F.col("node"), "left").select("fp", F.coalesce("root", "fp").alias("root"), "first", "copies")
    merged, merged_path = stored(merged)
    lowest, lowest_path = stored(merged.groupBy("root").agg(F.min("first").alias("component_id"), F.count("*").alias("_n")))
    named, _ = stored(looked_up(merged, lowest, "root").select("fp", "component_id", F.col("copies").alias("_n")))
    dropped(docs.sparkSession, kinds_path, merged_path, lowest_path)
    return looked_up(fps, named, "fp").select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
