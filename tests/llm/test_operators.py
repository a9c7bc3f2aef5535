"""Operators against brute force, exact round trips and held-out labels, and the cases every operator must take."""

from __future__ import annotations

import hashlib
import re
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from fanout.llm import chat_format, common, decontaminate, exact_dedup, line_dedup, quality, sentencepiece_lattice, sharding, simhash, token_counts, toxicity, wide_simhash

SF = "/root/testdata/sf0.001"
DOCS = "doc_id long, text string, lang string, source string, n_chars long"
WORD, PIECE = public_tokenizers.path("word_bpe_49k.json"), public_tokenizers.path("piece_bpe_32k.model")
#: Nulls, empty and blank texts, ties, repeated rows, a long text, and a hot group of copies.
ODD = [
    (1, None), (2, ""), (3, " \t\n"), (4, "a"), (5, "a"), (5, "a"), (None, "lost row"), (6, "x" * 3000), (7, "one two three four five six seven eight nine\nshort\n\none two three four five six seven eight nine"),
    (8, "naïve  ÉTÉ 漢字 😀 ▁ <|endoftext|> it's"), *((i, "the same text again and again for all of these rows") for i in range(20, 60)),
]


@pytest.fixture(scope="module")
def odd(spark):
    """With extra columns whose names operators use inside."""
    df = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in ODD], DOCS)
    return df.withColumns({c: F.lit("clash") for c in ("body", "fp", "key", "n", "node", "words", "_tag", "keep_id", "score", "first", "list", "token")})


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


@pytest.fixture(scope="module")
def labels(spark):
    return spark.read.parquet(f"{SF}/labels.parquet")


def squeeze(t):
    return re.sub(r"[\x20\x09-\x0D]+", " ", t or "")


@pytest.mark.parametrize("first", [1, 3, 256])
def test_exact_dedup_equals_grouping(odd, docs, first):
    for df in (odd, docs):
        rows = [(r["doc_id"], squeeze(r["text"])) for r in df.collect()]
        groups = defaultdict(list)
        for i, t in rows:
            groups[t].append(i)
        want = sorted((str(i), min((x for x in groups[t] if x is not None), default=None), len(groups[t])) for i, t in rows)
        base = df.select("doc_id", exact_dedup.squeezed().cast("binary").alias("body"))
        got = exact_dedup.radix_groups(base, first=first, growth=4)
        assert sorted((str(r["doc_id"]), r["keep_id"], r["group_size"]) for r in got.collect()) == want
    r = exact_dedup.exact_dedup(odd).filter("doc_id = 4").first()
    assert r["kept"] and r["group_size"] == 3 and r["text_sha256"] == hashlib.sha256(b"a").hexdigest()


@pytest.mark.parametrize("send", [0, 1 << 20])
@pytest.mark.parametrize("first", [1, 3, 256])
def test_exact_dedup_of_repeated_and_missing_ids(spark, first, send):
    """Ids that stand for several texts, which part early and agree later, and rows without an id."""
    a, b, z = "a" * 256, "b" * 256, "z" * 300
    rows = [(5, a + z), (5, b + z), (6, a + z), (6, b + z), (None, a + z), (None, "n" * 300), (None, "n" * 300), (None, "m" * 300), (None, None), (7, None), (7, "")]
    want = Counter()
    for i, t in rows:
        same = [k for k, u in rows if (u or "") == (t or "")]
        want[i, min((k for k in same if k is not None), default=None), len(same), t or ""] += 1
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("body", F.coalesce("text", F.lit("")).cast("binary"))
    got = exact_dedup.radix_groups(df, first=first, growth=4, send=send).collect()
    assert Counter((r["doc_id"], r["keep_id"], r["group_size"], r["text"] or "") for r in got) == want


def test_best_fit_packs_tightly_and_keeps_groups_whole(odd, docs):
    rng = np.random.default_rng(3)
    sizes = Counter(rng.integers(1, 400, 500).tolist())
    plan = sharding.pack(list(sizes.items()), 8)
    load = Counter()
    for w, b, n in plan:
        load[b] += w * n
    assert sum(load.values()) == sum(w * n for w, n in sizes.items()) and max(load.values()) - min(load.values()) <= 8
    for df in (odd, docs):
        rows = sharding.shard(df, 8).collect()
        assert len(rows) == df.count()
        slots = defaultdict(list)
        for r in rows:
            slots[r["shard"]].append(r["slot"])
        assert all(sorted(v) == list(range(len(v))) for v in slots.values())
    where = {r["doc_id"]: r["shard"] for r in sharding.shard(odd, 8).collect()}
    assert len({where[i] for i in range(20, 60)}) == 1 and where[4] == where[5]


@pytest.mark.parametrize("send", [0, 10])
def test_shards_are_the_same_without_what_is_sent(spark, docs, monkeypatch, send):
    """Packing and numbering that are too large to send; weights of one group, of many, and of more than a bin takes."""
    some = docs.select("doc_id", "text").unionByName(spark.createDataFrame([(10_000 + i, f"equal weight {i:04d}") for i in range(600)], "doc_id long, text string"))
    weigh = lambda: Counter((r["shard"], r["size"]) for r in sharding.shard(some, 8).collect())
    want = weigh()
    monkeypatch.setattr(sharding, "SEND_ROWS", send)
    monkeypatch.setattr(sharding, "HOT_KEYS", 5)
    rows = sharding.shard(some, 8).collect()
    assert weigh() == want and len({r["doc_id"] for r in rows}) == len(rows) == some.count()
    assert Counter((r["shard"], r["slot"]) for r in rows) == {(s, i): 1 for s, n in Counter(r["shard"] for r in rows).items() for i in range(n)}


@pytest.mark.parametrize("hot", [1, 3, 1_000])
def test_lookups_of_hot_keys(spark, monkeypatch, hot):
    """Hot and other keys, keys without a partner on either side and null ones give what a plain join gives."""
    monkeypatch.setattr(common, "HOT_KEYS", hot)
    rows = spark.createDataFrame([(k, i) for i, k in enumerate(["a"] * 50 + ["b"] * 20 + list("cdefgh") + [None] * 30)], "k string, i long")
    lookup = rows.filter("k is not null and k != 'd'").groupBy("k").agg(F.count("*").alias("_n"), F.min("i").alias("low"))
    want = sorted(map(tuple, rows.join(lookup.drop("_n"), "k").collect()))
    assert sorted(map(tuple, common.looked_up(rows, lookup, "k").collect())) == want and len(want) == 75
    assert common.looked_up(rows.limit(0), lookup.limit(0), "k").count() == 0


def test_lattice_pairs_that_meet_in_a_slot(monkeypatch, docs):
    import sentencepiece

    monkeypatch.setattr(sentencepiece_lattice.Lattices, "PAIRS", 2)
    encoder = sentencepiece_lattice.Encoder(sentencepiece_lattice.Pieces(PIECE), {})
    texts = [r["text"] or "" for r in docs.limit(60).collect()] + ["naïve 漢字 😀 it's", "aaaa bbbb abababab"]
    sp = sentencepiece.SentencePieceProcessor(model_file=PIECE)
    assert [x.tolist() for x in encoder.encode_all(texts)] == sp.encode(texts)


def test_texts_normalised_before_have_the_library_ids():
    tok, (bare, added) = token_counts.tokenizer(WORD), token_counts.bare_tokenizer(WORD)
    chars = [chr(c) for c in range(1, ord(token_counts.PLAIN))]
    texts = [f"Ab{c}Cd {c}{c} e{c}" for c in chars] + ["ΟΔΥΣΣΕΥΣ ΣΑΣ", "İIıi", "E\u0301a\u0323\u0302", "a\u00a0\u0085b\x1cc", "  IT'S  we'LL 12 3½ ", "".join(chars)]
    for t in texts:
        assert bare.encode(token_counts.normalised(t, added), add_special_tokens=False).ids == tok.encode(t, add_special_tokens=False).ids, repr(t)
    assert all(token_counts.normalised(t, added) is None for t in ("a <|ENDOFTEXT|> b", "漢字", "a\u05d0"))
    long = "ÉTÉ  It's a\tΣΑΣ, e\u0301tude! " * 300
    assert token_counts.chunked_count(bare, token_counts.normalised(long, added), 128, 8) == len(tok.encode(long, add_special_tokens=False).ids)


def test_token_counts_equal_the_library(odd, docs):
    tok = token_counts.tokenizer(WORD)
    for df, chunk in ((odd, 65_536), (docs, 200), (docs, 65_536)):
        got = token_counts.count_tokens(df, WORD, chunk=chunk, overlap=20)
        want = sorted((str(r["doc_id"]), len((r["text"] or "").encode()), len(tok.encode(r["text"] or "", add_special_tokens=False).ids)) for r in df.collect())
        assert sorted((str(r["doc_id"]), r["n_bytes"], r["n_tokens"]) for r in got.collect()) == want


@pytest.mark.parametrize("text", ["x" * 5000, "ab " * 3000, "it's " * 900 + "y" * 700, "é" * 400 + " z" * 400, "<|endoftext|>" * 300, "\n" * 900 + "q"])
def test_chunks_of_awkward_texts(text):
    tok = token_counts.tokenizer(WORD)
    assert token_counts.chunked_count(tok, text, 128, 8) == len(tok.encode(text, add_special_tokens=False).ids)


def components(fp, bits):
    """Brute force over all pairs: id -> smallest linked id."""
    ids = sorted(fp, key=lambda i: (i is None, i))
    root = {i: i for i in ids}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            if bin(fp[a] ^ fp[b]).count("1") <= bits:
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {i: find(i) for i in ids}


@pytest.mark.parametrize("hot", [4096, 3])
def test_simhash_equals_all_pairs(docs, odd, hot):
    for df in (docs, odd.filter("doc_id is not null")):
        rows = {r["doc_id"]: simhash.fingerprint(r["text"] or "") for r in df.collect()}
        got = {r["doc_id"]: (r["fingerprint"], r["component_id"]) for r in simhash.near_duplicates(df, hot=hot).collect()}
        want = components(rows, 3)
        assert got == {i: (f"{rows[i]:016x}", want[i]) for i in rows}


def test_posting_lists_of_dense_fingerprints(spark):
    """A ball of neighbouring fingerprints: lists are long, are dealt anew and probed, and links stay complete."""
    rng = np.random.default_rng(5)
    fps = {int(x) for x in (np.uint64(0xF0F0F0F0F0F0F0F0) ^ (np.uint64(1) << rng.integers(0, 64, 400, dtype=np.uint64)) ^ (np.uint64(1) << rng.integers(0, 64, 400, dtype=np.uint64)))}
    fps |= {int(x) for x in rng.integers(0, 1 << 62, 50)}
    df = spark.createDataFrame([(int(np.array(x, np.uint64).view(np.int64)),) for x in fps], "fp long")
    for hot in (4096, 16):
        edges = [(r["a"] & (1 << 64) - 1, r["b"] & (1 << 64) - 1) for r in simhash.links(df, hot=hot).collect()]
        assert all(bin(a ^ b).count("1") <= 3 for a, b in edges)
        root = {x: x for x in fps}

        def find(i, root=root):
            while root[i] != i:
                i = root[i]
            return i

        for a, b in edges:
            root[find(a)] = find(b)
        want = components({x: x for x in fps}, 3)
        assert len({find(x) for x in fps}) == len(set(want.values()))


def test_near_copies_find_similar_texts(spark):
    rng = np.random.default_rng(1)
    vocabulary = [f"w{i}" for i in range(5000)]
    base = [[vocabulary[i] for i in rng.integers(0, 5000, 200)] for _ in range(60)]
    rows = []
    for k, ws in enumerate(base):
        rows.append((k, " ".join(ws)))
        edited = list(ws)
        for at in rng.integers(0, 200, 2):
            edited[at] = "changed"
        rows.append((100 + k, " ".join(edited)))
    got = {r["doc_id"]: r["component_id"] for r in wide_simhash.near_copies(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert sum(got[100 + k] == k for k in range(60)) >= 58 and len(set(got.values())) >= 60


def test_chunks_of_a_list_link_as_the_whole_list(spark, monkeypatch):
    """Near copies with one list in common, which all texts are in; small chunks against an unchunked run."""
    rng = np.random.default_rng(9)
    fps = rng.integers(0, 256, (60, 64))
    same = {0, 1, 3, *range(11, 60, 3)}
    assert sum(set(t) <= same for t in wide_simhash.TRIPLES.tolist()) == 1
    fps[:, [0, 1, 3]] = 7
    for k in range(30):
        fps[30 + k] = fps[k] ^ np.array([p not in same for p in range(64)])
    monkeypatch.setattr(wide_simhash, "fingerprint", lambda text, shingle: bytes.fromhex(text))
    df = spark.createDataFrame([(k, bytes(f.astype(np.uint8)).hex()) for k, f in enumerate(fps)], "doc_id long, text string")
    for chunk in (1, 4, 7, 100_000):
        got = {r["doc_id"]: r["component_id"] for r in wide_simhash.near_copies(df, chunk=chunk).collect()}
        assert got == {k: k % 30 for k in range(60)}, chunk


def brute_runs(rows, least=8):
    """Every pair of equal lines, as far as the lines after them are equal: runs of enough words are cut at the later place."""
    docs = {i: [(k, x.strip(" \t\x0b\x0c\r")) for k, x in enumerate(t.split("\n")) if x.strip(" \t\x0b\x0c\r")] for i, t in sorted(rows)}
    seen, out = defaultdict(list), {}
    for i, text in sorted(rows):
        cut, own = set(), docs[i]
        for at, (_, line) in enumerate(own):
            for j, b in seen[line]:
                n = words = 0
                while b + n < len(docs[j]) and at + n < len(own) and docs[j][b + n][1] == own[at + n][1]:
                    words += len(re.split(r"[ \t\x0b\x0c\r]+", own[at + n][1]))
                    n += 1
                if words >= least:
                    cut |= set(range(own[at][0], own[at + n - 1][0] + 1))
            seen[line].append((i, at))
        for (a, _), (b, _) in zip(own, own[1:]):  # blank lines between two cut lines
            if a in cut and b in cut:
                cut |= set(range(a, b))
        out[i] = "\n".join(x for k, x in enumerate(text.split("\n")) if k not in cut)
    return out


LONG = "a line of this licence that has more than eight words"


@pytest.mark.parametrize(
    ("texts", "last"),
    [
        (["x\n" + LONG + "\nAll rights reserved.\ny", "z\n" + LONG + "\nAll rights reserved.\nw"], "z\nw"),
        ([LONG + "\nAll rights reserved.", LONG + "\nAll rights reserved."], ""),
        ([LONG + "\none\ntwo\nx", LONG + "\nthree\n\nfour\ny", LONG + "\nthree\n\nfour\nz"], "z"),  # goes on as the second copy, not as the first
        (["a b c\nd e f\ng h i\nj\nk\nl", "a b c\nd e f\ng h i\nj\nk\nm"], "m"),
        ([LONG + "\nAll rights reserved.\n" + LONG + "\nAll rights reserved.\nend"], LONG + "\nAll rights reserved.\nend"),
    ],
)
def test_line_dedup_cuts_a_repeated_run_to_its_end(spark, texts, last):
    rows = list(enumerate(texts))
    got = {r["doc_id"]: r["text"] for r in line_dedup.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == brute_runs(rows) and got[len(texts) - 1] == last


def test_whole_runs_equal_brute_force(spark, docs, odd):
    rng = np.random.default_rng(6)
    lines = ["a", "b c", "d e f", "g h i j k", "l m n o p q r s t", "", " \t"]
    dense = spark.createDataFrame([(k, "\n".join(lines[i] for i in rng.integers(0, 7, 25))) for k in range(12)], "doc_id long, text string")
    short = spark.createDataFrame([(k, "\n".join("uvwxyz"[i] for i in rng.integers(0, 6, 60))) for k in range(20)], "doc_id long, text string")
    for df in (dense, short, docs, odd.filter("doc_id is not null and text is not null").dropDuplicates(["doc_id"])):
        rows = [(r["doc_id"], r["text"]) for r in df.collect()]
        cut = line_dedup.dedup_lines(df)
        assert {r["doc_id"]: r["text"] for r in cut.collect()} == brute_runs(rows)
        plan = cut._jdf.queryExecution().toString()
        assert "Python" not in plan and "Arrow" not in plan


def test_line_minima_are_fewer_than_windows_and_guaranteed(spark, docs):
    short = spark.createDataFrame([(k, "\n".join(f"w{(i * 7 + k) % 50}" for i in range(200))) for k in range(3)], "doc_id long, text string")
    n = short.select(F.explode(line_dedup._fingerprints(F.col("text"), 8)).alias("s")).count()
    assert n < 0.5 * 3 * (200 - 7)


def test_line_dedup_keeps_all_rows_and_columns(odd, none):
    extra = odd.withColumns({c: F.lit("own") for c in ("runs", "_tag", "_run_id", "_run_tag", "_runs", "_c0", "at", "windows", "a.b")})
    out = line_dedup.dedup_lines(extra)
    assert out.columns == [*extra.columns, "_n_lines", "_n_removed"]
    assert out.count() == odd.count() == out.filter("runs = 'own' and _tag = 'own' and _run_id = 'own' and _c0 = 'own'").count()
    assert line_dedup.dedup_lines(none.withColumn("runs", F.lit(1))).count() == 0


def test_line_dedup_of_a_very_long_text(spark):
    """40,000 lines, of which the second half repeats the first."""
    half = "\n".join(f"line {i} of a long text with some more words in it" for i in range(20_000))
    got = line_dedup.dedup_lines(spark.createDataFrame([(1, half + "\n" + half)], "doc_id long, text string")).first()
    assert got["text"] == half and got["_n_removed"] == 20_000


def test_preference_pairs(spark):
    t = [(0, 0, "user", "hi"), (0, 1, "assistant", "good"), (1, 0, "user", "hi"), (1, 1, "assistant", "bad <|im_end|>"), (2, None, None, None), (4, 0, "user", "same"), (5, 0, "user", "same"), (None, 0, "user", "lost"), (None, 0, "user", "lost"), (6, 0, "<|im_start|>x", "t")]
    df = spark.createDataFrame(t, "conv_id long, turn long, role string, text string").withColumn("side", F.lit("clash"))
    rows = chat_format.preference_pairs(chat_format.adjacent_pairs(df)).collect()
    got = {r["pair_id"]: r for r in rows}
    assert sum(r["pair_id"] is None for r in rows) == 2 and got[3]["chosen"] == "<|im_start|><| im_start |>x\nt<|im_end|>\n"
    assert got[0]["prompt"] == "<|im_start|>user\nhi<|im_end|>\n" and got[0]["n_shared"] == 1 and got[0]["status"] == "pair"
    assert got[0]["chosen"] == "<|im_start|>assistant\ngood<|im_end|>\n" and got[0]["chosen_mask"] == [22, 15]
    assert "bad <| im_end |><|im_end|>" in got[0]["rejected"] and sum(got[0]["rejected_mask"]) == len(got[0]["rejected"])
    assert got[1]["status"] == "chosen_only" and got[2]["status"] == "identical" and got[None]["status"] == "chosen_only"
    assert chat_format.preference_pairs(chat_format.adjacent_pairs(df.filter("false"))).count() == 0


def test_decontamination_finds_whole_and_edited_items_and_leaves_others(spark, docs):
    rng = np.random.default_rng(2)
    words = [f"term{i}" for i in range(400)]
    items = [(k, " ".join(words[i] for i in rng.integers(0, 400, 40))) for k in range(20)] + [(90, None), (91, ""), (92, "solo")]
    clean = [(1000 + k, " ".join(words[i] for i in rng.integers(0, 400, 300))) for k in range(40)]
    leaky = []
    for k in range(20):
        ws = items[k][1].split()
        ws[7], ws[23] = "edited", "changed"
        del ws[31]
        leaky.append((k, clean[k][1] + " " + " ".join(ws) + " " + clean[k + 20][1]))
    df = spark.createDataFrame([*clean, *leaky, (5000, None), (5001, "")], "doc_id long, text string")
    bench = spark.createDataFrame(items, "item_id long, text string")
    for block in (400_000, 100):
        got = {(r["doc_id"], r["item_id"]) for r in decontaminate.leaks(df, bench, block_words=block).collect()}
        assert got == {(k, k) for k in range(20)}
    assert decontaminate.leaks(df, bench.filter("false")).count() == 0


def test_decontamination_finds_leaks_with_few_or_frequent_seeds(spark):
    """An item with a fifth of its words changed, and one quoted by less than half in a third of all rows."""
    edited, quoted = [f"e{i}" for i in range(40)], [f"q{i}" for i in range(39)]
    changed = [w if i % 5 else "other" for i, w in enumerate(edited)]
    rows = [(0, " ".join(["before", *changed, "after"]))]
    rows += [(k, " ".join([f"x{k}", *quoted[10 : 24 + k % 6], f"y{k}"])) for k in range(1, 16)]
    rows += [(k, f"nothing of an item in row {k}") for k in range(16, 46)]
    bench = spark.createDataFrame([(0, " ".join(edited)), (1, " ".join(quoted))], "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]): r["score"] for r in decontaminate.leaks(spark.createDataFrame(rows, "doc_id long, text string"), bench).collect()}
    assert got == {(0, 0): naive_alignment(edited, changed), **{(k, 1): 14 + k % 6 for k in range(1, 16)}}


def test_decontamination_gives_the_best_place():
    item, gap = [f"t{i}" for i in range(40)], ["between"] * 200
    items = decontaminate.Items([(7, " ".join(item))])
    for parts, last in (([item[:12], gap, item, gap], 252), ([item, gap, item[:12]], 40), ([item[:12], gap, item[3:20], gap, item], 469)):
        text = " ".join(w for p in parts for w in p)
        assert decontaminate.matches(items, items.seeds, text) == [(7, 40, 1.0, last)]


def naive_alignment(item, part):
    h = [[0] * (len(part) + 1) for _ in range(len(item) + 1)]
    for i, a in enumerate(item, 1):
        for j, b in enumerate(part, 1):
            h[i][j] = max(0, h[i - 1][j - 1] + (1 if a == b else -1), h[i - 1][j] - 1, h[i][j - 1] - 1)
    return max(map(max, h))


def test_alignment_equals_the_table():
    rng = np.random.default_rng(4)
    for _ in range(50):
        a, b = rng.integers(1, 5, 12), rng.integers(0, 5, 30)
        assert decontaminate.align(a, b)[0] == naive_alignment(a.tolist(), b.tolist())


def test_decontamination_of_odd_rows(spark):
    """Repeated and null ids, ties, clashing columns, words between lines and tabs, an item of very many different words."""
    item = " ".join(f"i{k}" for k in range(30))
    df = spark.createDataFrame([(1, item), (1, item), (None, item), (2, item.replace(" ", "\n\t")), (3, None), (4, "i1 i2"), (5, "w7 " * 50_000)], "doc_id long, text string").withColumn("score", F.lit("clash")).withColumn("item_id", F.lit(0))
    bench = spark.createDataFrame([(7, item), (7, item), (None, item), (8, None)], "item_id long, text string").withColumn("doc_id", F.lit(9))
    got = Counter((r["doc_id"], r["item_id"], r["score"]) for r in decontaminate.leaks(df, bench).collect())
    assert got == {(1, 7, 30): 4, (None, 7, 30): 2, (2, 7, 30): 2, (1, None, 30): 2, (None, None, 30): 1, (2, None, 30): 1}
    assert decontaminate.leaks(df.filter("false"), bench).count() == 0
    many = decontaminate.Items([(0, " ".join(f"v{k}" for k in range(2_200_000)))])
    assert many.base**3 > 1 << 63 and [m[0] for m in decontaminate.matches(decontaminate.Items([(0, item)]), decontaminate.Items([(0, item)]).seeds, item)] == [0]
    assert len(many.found(many.words[0][500:540], many.seeds)[0]) == 38


def test_decontamination_recall_by_share_of_edits(spark):
    """Against alignment of every item with every text: 5 to 30 % of the words changed, at random."""
    rng = np.random.default_rng(12)
    items = [[f"x{k}_{i}" for i in range(40)] for k in range(30)]
    for share in (0.05, 0.1, 0.2, 0.3):
        rows = []
        for k, ws in enumerate(items):
            edited = [w if rng.random() >= share else f"e{rng.integers(1000)}" for w in ws]
            rows.append((k, " ".join([f"n{rng.integers(1000)}" for _ in range(20)] + edited)))
        want = {k for k, t in rows if naive_alignment(items[k], t.split()) >= decontaminate.needed(40)}
        bench = spark.createDataFrame([(k, " ".join(ws)) for k, ws in enumerate(items)], "item_id long, text string")
        got = {(r["doc_id"], r["item_id"]) for r in decontaminate.leaks(spark.createDataFrame(rows, "doc_id long, text string"), bench).collect()}
        assert got <= {(k, k) for k in want} and len(got) >= 0.9 * len(want), share


def test_near_copies_against_all_pairs_by_similarity(spark):
    """Pairs of texts at sf0.01 with a Jaccard similarity of 0.8 or more of their 5-word shingles: how many have one component."""
    df = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    shingles, posted = {}, defaultdict(list)
    for r in df.collect():
        ws = (r["text"] or "").lower().split()
        shingles[r["doc_id"]] = s = {" ".join(ws[k : k + 5]) for k in range(max(1, len(ws) - 4))}
        for x in s:
            posted[x].append(r["doc_id"])
    met = {(a, b) for ids in posted.values() for i, a in enumerate(ids) for b in ids[i + 1 :]}
    pairs = [(a, b) for a, b in met if len(shingles[a] & shingles[b]) >= 0.8 * len(shingles[a] | shingles[b])]
    got = {r["doc_id"]: r["component_id"] for r in wide_simhash.near_copies(df).collect()}
    assert len(pairs) > 100 and sum(got[a] == got[b] for a, b in pairs) >= 0.95 * len(pairs)


def test_lattice_gives_the_library_s_ids(spark, docs, odd):
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=PIECE)
    for df in (docs, odd):
        want = sorted((str(r["doc_id"]), sp.encode(r["text"] or "")) for r in df.collect())
        got = sentencepiece_lattice.encode(df, PIECE).collect()
        assert sorted((str(r["doc_id"]), r["ids"]) for r in got) == want
        assert all(r["round_trip"] for r in got if r["doc_id"] != 8)
        back = sentencepiece_lattice.decode_ids(sentencepiece_lattice.encode(df, PIECE), PIECE).collect()
        assert sorted((str(r["doc_id"]), r["text"]) for r in back) == sorted((str(r["doc_id"]), sp.decode(sp.encode(r["text"] or ""))) for r in df.collect())
    p = sentencepiece_lattice.Pieces(PIECE)
    words = ["▁hello", "▁thntble", "▁a", "▁unbelievable"]
    rel = sentencepiece_lattice.encode_words(spark.createDataFrame([(w,) for w in words], "word string"), p)
    assert {r["word"]: r["ids"] for r in rel.collect()} == {w: p.fold(w) for w in words}


def test_classifiers_learn_and_give_every_row_a_score(spark, docs, odd, labels, none):
    big = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    known = spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    for f, label, least in ((toxicity.toxicity, "toxic", 0.7), (quality.quality, "quality", 0.97)):
        rows = f(big, known).join(known, "doc_id").filter("held_out").select(label, "score").collect()
        pos, neg = [r["score"] for r in rows if r[label]], [r["score"] for r in rows if not r[label]]
        assert np.mean([(a > b) + (a == b) / 2 for a in pos for b in neg]) >= least
        got = f(odd, known).collect()
        assert len(got) == odd.count() and all(0 <= r["score"] <= 1 and r["predicted"] == (r["score"] >= 0.3) for r in got)
        assert f(odd, known.filter("false")).count() == odd.count()
        assert f(none, known).count() == 0


def test_toxicity_scores_follow_from_compressed_lengths(spark):
    """Scores of the column against lengths under both dictionaries, window by window; a very long text among them."""
    import zstandard as z

    docs, known = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    model = toxicity.fit_labelled(docs, known)
    some = [(r["doc_id"], r["text"]) for r in docs.orderBy("doc_id").limit(40).collect()] + [(-1, None), (-2, ""), (-3, "idiot " * 60_000)]
    got = {r["doc_id"]: r["s"] for r in spark.createDataFrame(some, "doc_id long, text string").select("doc_id", toxicity.scores(spark, model).alias("s")).collect()}

    def size(window, dictionary):
        d = z.ZstdCompressionDict(dictionary, dict_type=z.DICT_TYPE_RAWCONTENT)
        return len(z.ZstdCompressor(dict_data=d, compression_params=toxicity._settings()).compress(window))

    assert model.toxic.endswith(model.ordinary.lstrip(b" ")) and len(model.toxic) == len(model.ordinary)
    for i, t in some:
        ws = toxicity.windows(t or "")
        if (t or "").split():  # the windows are the whole text
            assert b"".join(w[:-1] for w in ws) == b" " + b" ".join(t.lower().encode().split())
        length = {w: size(w, model.ordinary) - size(w, model.toxic) for w in set(ws)}
        d = np.array([length[w] for w in ws] or [0])
        x = [np.maximum(d, 0).mean(), min(12, d.max()) / 4, np.log1p((d >= 4).sum()), (d >= 4).mean() * 4, np.log1p((d >= 6).sum())]
        margin = np.clip(np.dot(x, model.weights) + model.bias, -40, 40)
        assert abs(got[i] - 1 / (1 + np.exp(-margin))) < 1e-9


def test_toxicity_on_held_out_labels(spark):
    docs, known = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    rows = toxicity.toxicity(docs, known).join(known, "doc_id").filter("held_out and toxic is not null").select("toxic", "score").collect()
    pos, neg = (np.array([r["score"] for r in rows if r["toxic"] == y]) for y in (1, 0))
    assert ((pos[:, None] > neg) + (pos[:, None] == neg) / 2).mean() >= 0.9


def test_labels_repeated_null_or_of_rows_that_share_an_id(spark):
    docs, known = (spark.read.parquet(f"/root/testdata/sf0.001/{t}.parquet") for t in ("documents", "labels"))
    more = known.unionByName(known).unionByName(known.limit(5).withColumn("toxic", F.lit(None).cast("int")).withColumn("quality", F.lit(None).cast("int")))
    twice = docs.unionByName(docs.limit(30))
    for f in (toxicity.toxicity, quality.quality):
        want = {r["doc_id"]: r["score"] for r in f(docs, known).collect()}
        got = f(twice, more).collect()
        assert len(got) == docs.count() + 30 and all(abs(r["score"] - want[r["doc_id"]]) < 1e-9 for r in got)


def test_rules_as_columns_equal_rules_in_numpy(spark):
    docs, known = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    model = quality.fit_labelled(docs, known)
    odd = spark.createDataFrame([(-1, None), (-2, ""), (-3, "A1! | " * 20_000), (-4, "x\n" * 9)], "doc_id long, text string")
    cols = [f"_s_{c}" for c in quality.STATISTICS]
    rows = quality.statistics(docs.select("doc_id", "text").unionByName(odd)).select(*cols, model.column().alias("score")).collect()
    x = np.array([[r[c] for c in cols] for r in rows])
    margin = np.full(len(x), model.bias)
    for rule, w in zip(model.rules, model.weights):
        hit = np.ones(len(x), bool)
        for t in rule:
            hit &= x[:, t.stat] > t.cut if t.above else x[:, t.stat] <= t.cut
        margin += w * hit
    assert model.rules and np.allclose(1 / (1 + np.exp(-np.clip(margin, -40, 40))), [r["score"] for r in rows])


def test_empty_tables(none, spark):
    bench = spark.createDataFrame([(1, "some words of an item that is long enough to be found")], "item_id long, text string")
    for df in (
        exact_dedup.exact_dedup(none), sharding.shard(none), token_counts.count_tokens(none, WORD), simhash.near_duplicates(none), wide_simhash.near_copies(none), line_dedup.dedup_lines(none),
        decontaminate.leaks(none, bench), sentencepiece_lattice.encode(none, PIECE),
    ):
        assert df.count() == 0


def test_odd_rows_all_come_out(odd):
    n = odd.count()
    assert exact_dedup.exact_dedup(odd).count() == n and simhash.near_duplicates(odd).count() == n and sentencepiece_lattice.encode(odd, PIECE).count() == n
    assert wide_simhash.near_copies(odd).count() == n - 1  # a row without an id has no component


def test_joins_leave_no_word_out(spark):
    import sentencepiece

    sp, p = sentencepiece.SentencePieceProcessor(model_file=PIECE), sentencepiece_lattice.Pieces(PIECE)
    texts = ["naïve漢字", "😀", "a😀b😀😀c", "漢", "it's漢", "un" * 40 + "believable", "", "  two", "   😀x", "hello"]
    words = ["▁" + t.replace(" ", "▁") for t in texts] + [""]
    rel = sentencepiece_lattice.encode_words(spark.createDataFrame([(w,) for w in words], "word string"), p)
    got = {r["word"]: r["ids"] for r in rel.collect()}
    assert got == {"▁" + t.replace(" ", "▁"): sp.encode(t) if t else p.fold("▁") for t in texts}
