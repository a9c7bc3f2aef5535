"""The pipeline's stages in order, each held against what it promises on its own input."""

from __future__ import annotations

import public_tokenizers

import corpus_pipeline
from fanout.llm import decontaminate, simhash, toxicity, wide_simhash

SF = "/root/testdata/sf0.001"


def test_line_stage_cuts_short_last_lines_of_a_run(spark):
    text = "a line of this licence that has more than eight words\nAll rights reserved."
    df = spark.createDataFrame([(1, text, "en", "s", 0), (2, text + "\nown", "en", "s", 0)], "doc_id long, text string, lang string, source string, n_chars long")
    assert {r["doc_id"]: r["text"] for r in corpus_pipeline.without_repeated_lines(spark, df, SF).collect()} == {1: text, 2: "own"}


def test_stages(spark, tmp_path):
    import sentencepiece

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    bench = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    columns, kept = docs.columns, {}
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "line_dedup", "simhash_near_dedup", "decontamination", "sentencepiece"]
    for name, stage in corpus_pipeline.STAGES:
        stage(spark, docs, SF).write.parquet(str(tmp_path / name))
        before, docs = {r["doc_id"]: r["text"] for r in docs.collect()}, spark.read.parquet(str(tmp_path / name))
        kept[name] = before, docs
        if name != "sentencepiece":
            assert docs.columns == columns
    before, after = kept["toxicity"]
    model = toxicity.fit_labelled(spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet"))
    assert {r["doc_id"] for r in after.collect()} == {i for i, t in before.items() if model.score(t or "") < 0.3}
    before, after = kept["line_dedup"]
    assert {r["doc_id"] for r in after.collect()} == set(before)
    before, after = kept["simhash_near_dedup"]
    left, fp = {r["doc_id"] for r in after.collect()}, {i: wide_simhash.fingerprint(t or "") for i, t in before.items()}
    for i in set(before) - left:  # what went has something like it among what was there before it
        assert any(j < i and bin(int.from_bytes(fp[i]) ^ int.from_bytes(fp[j])).count("1") <= wide_simhash.most_bits(0.8) for j in before)
    assert len({fp[i] for i in left}) == len(left)
    before, after = kept["decontamination"]
    items = decontaminate.Items(bench)
    leaky = {i for i, t in before.items() if decontaminate.matches(items, items.seeds, t or "")}
    assert {r["doc_id"] for r in after.collect()} == set(before) - leaky
    before, after = kept["sentencepiece"]
    sp = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path("piece_bpe_32k.model"))
    assert {r["doc_id"]: r["ids"] for r in after.collect()} == {i: sp.encode(t or "") for i, t in before.items()}
    assert simhash.fingerprint("") == 0


def test_stages_take_odd_rows_and_empty_tables(spark, tmp_path):
    """Nulls in any column, empty and repeated rows, a long text, clashing columns; then no rows at all."""
    text = "these are some words of a text that is neither long nor toxic nor like another one"
    rows = [(1, None, None, None, None), (None, text, "en", "s", 5), (2, "", "en", "s", 0), (3, text, "en", "s", 5), (3, text, "en", "s", 5), (4, text + " again", None, "s", None), (5, "word " * 40_000, "en", "s", 9)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    docs = docs.withColumns({c: docs["doc_id"] for c in ("_tag", "runs", "score", "item_id", "component_id", "fp", "ids", "_score")})
    known = spark.createDataFrame([(3, 1, 0), (3, None, None), (None, 1, 1), (5, 0, 1)], "doc_id long, quality int, toxic int")
    for name, df in (("documents", docs), ("labels", known), ("benchmark", spark.createDataFrame([(1, None), (None, ""), (2, "a b c")], "item_id long, text string"))):
        df.write.parquet(f"{tmp_path}/odd/{name}.parquet")
        df.filter("false").write.parquet(f"{tmp_path}/none/{name}.parquet")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, f"{tmp_path}/odd").columns == docs.columns
        assert stage(spark, docs.filter("false"), f"{tmp_path}/none").count() == 0
    out = corpus_pipeline.run(spark, f"{tmp_path}/odd").collect()
    assert {r["doc_id"] for r in out} <= {1, 2, 3, 4, 5, None} and all(r["n_tokens"] == len(r["ids"]) for r in out)
    assert corpus_pipeline.run(spark, f"{tmp_path}/none").count() == 0
