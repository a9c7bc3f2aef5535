"""Near copies by word shingles and similarity, over SimHash fingerprints of 64 bytes.

Two texts with Jaccard similarity j of their shingle sets differ in a share of at most arccos(2j / (1 + j)) / pi of the
fingerprint's bits, give or take the spread of as many draws. Posting lists hold the texts with the same three bytes at the
same three places; 128 triples of places are listed, and texts of similarity 0.8 meet in 2.5 of them on average. In a list the
shared bytes of a pair are tallied, and pairs with enough of them are verified by their bits. A list gives the edges of a
forest, never all its pairs. One with more than CHUNK members is cut into chunks, and each chunk is also compared with each
other one as a block of its own, so all pairs of a list are tallied at any size; no task holds more than two chunks of a list.
"""

from __future__ import annotations

from collections.abc import Iterator
from math import acos, ceil, pi, sqrt

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import dropped, looked_up, stored, whole
from .simhash import components

PLACES, SHINGLE, SIMILARITY, CHUNK = 64, 5, 0.8, 2_048
STEPS = ((1, 3), (7, 19))
TRIPLES = np.array([(i, (i + a) % PLACES, (i + b) % PLACES) for a, b in STEPS for i in range(PLACES)])
LEAST_SHARED = 6


def _mixed(h: np.ndarray, k: int) -> np.ndarray:
    """The k-th 64 bits derived from each hash."""
    x = h + np.uint64((0x9E3779B97F4A7C15 * (k + 1)) & 0xFFFFFFFFFFFFFFFF)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def fingerprint(text: str, shingle: int = SHINGLE) -> bytes:
    """64 bytes over the different shingles of the words in lower case; fewer words are one shingle; no words: zeros."""
    import xxhash

    words = text.lower().encode().split()
    if not words:
        return bytes(PLACES)
    n = max(1, len(words) - shingle + 1)
    flat = b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words]) - 1
    starts, stops, h = [0, *(ends[: n - 1] + 1).tolist()], ends[min(shingle, len(words)) - 1 :].tolist(), xxhash.xxh64_intdigest
    hashes = np.unique(np.fromiter((h(flat[a:b]) for a, b in zip(starts, stops)), np.uint64, n))
    ones = np.zeros(8 * PLACES, np.int64)
    for at in range(0, len(hashes), 1 << 15):
        part = hashes[at : at + (1 << 15)]
        for k in range(PLACES // 8):
            ones[64 * k : 64 * k + 64] += np.unpackbits(_mixed(part, k).view(np.uint8)).reshape(-1, 64).sum(0, dtype=np.int64)
    return np.packbits(ones * 2 > len(hashes)).tobytes()


def most_bits(similarity: float) -> int:
    """Bits by which texts of this similarity differ at most, but for one in forty."""
    p = acos(2 * similarity / (1 + similarity)) / pi
    return ceil(8 * PLACES * p + 2 * sqrt(8 * PLACES * p * (1 - p)))


def forest(fp: np.ndarray, bits: int, cut: int = 0) -> list[tuple[int, int]]:
    """Edges over rows of fp (uint8, n x 64) that connect what pairs within `bits` bits connect; with a cut: pairs of a row before and one after it."""
    words, root, out = fp.view(np.uint64), np.arange(len(fp)), []
    for i in range(cut or len(fp) - 1):
        other = cut + np.flatnonzero(root[cut:] != root[i])  # what is connected needs no look
        if not len(other):
            continue
        other = other[(fp[other] == fp[i]).sum(1) >= LEAST_SHARED]
        other = other[np.bitwise_count(words[other] ^ words[i]).sum(1) <= bits]
        for j in other.tolist():
            if root[j] != root[i]:
                root[root == root[j]] = root[i]
                out.append((i, j))
    return out


def _runs(batches: Iterator[pd.DataFrame], key: str) -> Iterator[pd.DataFrame]:
    """Sorted batches cut so that no run of a key is torn."""
    held: list[pd.DataFrame] = []
    for b in batches:
        if not len(b):
            continue
        k = b[key].to_numpy()
        cut = int(np.searchsorted(k, k[-1]))
        if cut:
            yield pd.concat([*held, b.iloc[:cut]]) if held else b.iloc[:cut]
            held = [b.iloc[cut:]]
        elif held and held[0][key].iloc[0] != k[0]:
            yield pd.concat(held)
            held = [b]
        else:
            held.append(b)
    if held:
        yield pd.concat(held)


def near_copies(docs: DataFrame, shingle: int = SHINGLE, similarity: float = SIMILARITY, key: str = "doc_id", text: str = "text", chunk: int = CHUNK) -> DataFrame:
    """documents -> doc_id, component_id: the smallest doc_id of the near copies that hang together, for every input row.

    Null texts are empty; all texts without words are copies of each other. Texts with equal fingerprints are combined
    first, so copies cost nothing further on. Rows without a doc_id have no component (null). Repeated rows come out each.
    """
    bits, kind = most_bits(similarity), docs.schema[key].dataType.simpleString()
    spark = docs.sparkSession

    def of(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield pd.DataFrame({"doc_id": b["doc_id"], "fp": [fingerprint(t, shingle) for t in b["_text"]]})

    fps, _ = stored(docs.select(F.col(key).alias("doc_id"), whole(text).alias("_text")).filter("doc_id is not null").mapInPandas(of, f"doc_id {kind}, fp binary"))
    kinds, _ = stored(fps.groupBy("fp").agg(F.min("doc_id").alias("node"), F.count("*").alias("copies")))

    def listed(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        tag = np.arange(len(TRIPLES), dtype=np.int64) << 24
        for b in batches:
            for at in range(0, len(b), 2_000):
                part = b.iloc[at : at + 2_000]
                f = np.frombuffer(b"".join(part["fp"]), np.uint8).reshape(-1, PLACES).astype(np.int64)
                keys = tag + (f[:, TRIPLES[:, 0]] << 16) + (f[:, TRIPLES[:, 1]] << 8) + f[:, TRIPLES[:, 2]]
                yield pd.DataFrame({"list": keys.ravel(), "node": np.repeat(part["node"].to_numpy(), len(TRIPLES))})

    def met(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        last, first, count = None, None, 0
        for b in batches:  # runs may be of any length: only their first member is remembered, until a second one comes
            keys, nodes = b["list"].to_numpy(), b["node"].to_numpy()
            out: list[tuple[int, int, int]] = []
            edge = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
            for s, e in zip(edge.tolist(), [*edge[1:].tolist(), len(keys)]):
                k = int(keys[s])
                if k != last:
                    last, first, count = k, nodes[s], 1
                    s += 1
                for n in nodes[s:e]:
                    if count == 1:
                        out.append((k, 0, first))
                    out.append((k, count // chunk, n))
                    count += 1
                if count > chunk << 16:
                    raise ValueError("a list has more than 65,536 chunks; take a larger chunk")
            if out:
                yield pd.DataFrame(out, columns=["list", "part", "node"])

    lists = kinds.select("fp", "node").mapInPandas(listed, f"list long, node {kind}").repartition("list").sortWithinPartitions("list", "node").mapInPandas(met, f"list long, part long, node {kind}")
    lists, lists_path = stored(lists)
    # blocks of a list: each chunk alone, and each two chunks of it, where side 1 is the later one
    tops, _ = stored(lists.filter("part > 0").groupBy("list").agg(F.max("part").alias("top")))
    other = lists.join(tops, "list").withColumn("with", F.explode(F.sequence(F.lit(0), "top"))).filter("with != part")
    blocks = lists.select("list", F.col("part").alias("a"), F.col("part").alias("b"), F.lit(0).alias("side"), "node").unionByName(
        other.select("list", F.least("part", "with").alias("a"), F.greatest("part", "with").alias("b"), (F.col("part") > F.col("with")).cast("int").alias("side"), "node")
    )

    def linked(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in _runs(batches, "block"):
            keys, nodes, side = b["block"].to_numpy(), b["node"].to_numpy(), b["side"].to_numpy()
            fp = np.frombuffer(b"".join(b["fp"]), np.uint8).reshape(-1, PLACES)
            edge = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
            size = np.diff(np.r_[edge, len(keys)])
            two = edge[size == 2]
            near = two[np.bitwise_count(fp[two].view(np.uint64) ^ fp[two + 1].view(np.uint64)).sum(1) <= bits]
            a, c = [nodes[near]], [nodes[near + 1]]
            for s, n in zip(edge[size > 2].tolist(), size[size > 2].tolist()):
                cut = int(np.count_nonzero(side[s : s + n] == 0)) % n  # 0 where all are of one chunk
                if pairs := np.array(forest(np.ascontiguousarray(fp[s : s + n]), bits, cut), np.int64).reshape(-1, 2).tolist():
                    i, j = np.array(pairs).T
                    a.append(nodes[s + i])
                    c.append(nodes[s + j])
            yield pd.DataFrame({"a": np.concatenate(a), "b": np.concatenate(c)})

    block = F.shiftleft("list", 32).bitwiseOR(F.shiftleft("a", 16)).bitwiseOR(F.col("b"))  # 31, 16 and 16 bits
    dealt = blocks.select(block.alias("block"), "side", "node").join(kinds.select("fp", "node"), "node").select("block", "side", "node", "fp").repartition("block").sortWithinPartitions("block", "side", "node")
    edges, _ = stored(dealt.mapInPandas(linked, f"a {kind}, b {kind}").filter("a != b").distinct())
    dropped(spark, lists_path)
    roots, _ = stored(components(edges))
    named, _ = stored(kinds.join(roots, "node", "left").select("fp", F.coalesce("root", "node").alias("component_id"), F.col("copies").alias("_n")))
    return looked_up(fps, named, "fp").select("doc_id", "component_id")


def one_of_each(docs: DataFrame, **how) -> DataFrame:
    """documents -> their rows, but of near copies only those of the smallest doc_id. Rows without a doc_id stay."""
    gone, _ = stored(near_copies(docs, **how).filter("component_id != doc_id").select("doc_id").distinct())
    return docs.join(gone, "doc_id", "left_anti")
