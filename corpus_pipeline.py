"""The text pipeline: toxicity, line dedup, near-dedup, decontamination, tokens. Each stage is written and read again."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fanout.llm import decontaminate, line_dedup, sentencepiece_lattice, toxicity, wide_simhash
from fanout.llm.common import dropped, shared_dir, table, tables
from fanout.llm.learning import THRESHOLD


def without_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects documents that score 0.3 or more; the model learns from the labelled rows of `docs`."""
    model = toxicity.fit_labelled(docs, table(spark, sf_dir, "labels"))
    return docs.filter(toxicity.scores(spark, model) < THRESHOLD)


def without_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cuts runs of lines that occur earlier; n_chars is the new length. All rows stay, some with an empty text."""
    cut = line_dedup.dedup_lines(docs)
    return cut.withColumn("n_chars", F.when(F.col("_n_removed") > 0, F.length("text")).otherwise(F.col("n_chars")).cast("long")).select(docs.columns)


def without_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the smallest doc_id of each group of texts with a similarity of 0.8 in shingles of five words."""
    return wide_simhash.one_of_each(docs).select(docs.columns)


def without_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that hold a benchmark item, as it is or edited."""
    leaky = decontaminate.leaks(docs, table(spark, sf_dir, "benchmark")).select("doc_id").distinct()
    return docs.join(leaky, "doc_id", "left_anti").select(docs.columns)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids, round_trip of every document."""
    import public_tokenizers

    return sentencepiece_lattice.encode(docs, public_tokenizers.path("piece_bpe_32k.model"))


STAGES = [
    ("toxicity", without_toxic),
    ("line_dedup", without_repeated_lines),
    ("simhash_near_dedup", without_near_copies),
    ("decontamination", without_leaks),
    ("sentencepiece", tokens),
]

#: Compression, alignment and a lattice are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the table documents. What a stage stored for itself is deleted once its result is written."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        path, others = f"{shared_dir(spark)}/pipeline/{uuid.uuid4().hex}/{name}", set(tables())
        stage(spark, docs, sf_dir).write.parquet(path)
        dropped(spark, *(t for t in tables() if t not in others))
        docs = spark.read.parquet(path)
    return docs
