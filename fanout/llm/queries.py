"""The registered queries of this subpackage and, where SQL can say it, their DuckDB text."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat_format, decontaminate, exact_dedup, line_dedup, quality, sentencepiece_lattice, sharding, simhash, token_counts, toxicity
from .common import table


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op2_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return sentencepiece_lattice.encode(table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"))


def op3_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat_format.preference_pairs(chat_format.adjacent_pairs(table(spark, sf_dir, "conversations")))


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = line_dedup.dedup_lines(table(spark, sf_dir, "documents"))
    return out.select("doc_id", F.col("_n_lines").alias("n_lines"), F.col("_n_removed").alias("n_removed"), "text")


def op5_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op6_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def op7_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_dedup(table(spark, sf_dir, "documents"))


def op8_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard(table(spark, sf_dir, "documents"), 8)


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return token_counts.count_tokens(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (op1_toxicity, op2_sentencepiece, op3_chat_formatting, op4_line_dedup, op5_decontamination, op6_simhash_near_dedup, op7_exact_dedup, op8_sharding, op9_token_counts, op10_quality)
}

ORACLE_SQL: dict[str, str] = {
    "op3_chat_formatting": r"""
        WITH t AS (
            SELECT conv_id // 2 AS pair_id, coalesce(CAST(conv_id // 2 AS VARCHAR), 'lone ' || row_number() OVER ()) AS g, coalesce(conv_id % 2, 0) AS side, turn,
                   replace(replace(coalesce(role, ''), '<|im_start|>', '<| im_start |>'), '<|im_end|>', '<| im_end |>') AS role,
                   replace(replace(coalesce(text, ''), '<|im_start|>', '<| im_start |>'), '<|im_end|>', '<| im_end |>') AS text
            FROM conversations
        ), r AS (
            SELECT *, row_number() OVER (PARTITION BY g, side ORDER BY turn NULLS FIRST, role, text) AS k FROM t
        ), same AS (
            SELECT a.g, a.k FROM r a JOIN r b ON a.g = b.g AND a.k = b.k AND a.side = 0 AND b.side = 1 AND a.role = b.role AND a.text = b.text
        ), shared AS (
            SELECT g, count(*) AS n FROM (SELECT g, k, row_number() OVER (PARTITION BY g ORDER BY k) AS j FROM same) WHERE j = k GROUP BY g
        ), p AS (
            SELECT any_value(r.pair_id) AS pair_id, coalesce(max(n), 0) AS n_shared, count(*) FILTER (side = 0) AS nc, count(*) FILTER (side = 1) AS nr,
                   coalesce(string_agg(m, '' ORDER BY k) FILTER (side = 0 AND k <= coalesce(n, 0)), '') AS prompt,
                   coalesce(string_agg(m, '' ORDER BY k) FILTER (side = 0 AND k > coalesce(n, 0)), '') AS chosen,
                   coalesce(string_agg(m, '' ORDER BY k) FILTER (side = 1 AND k > coalesce(n, 0)), '') AS rejected,
                   coalesce(flatten(list(mask ORDER BY k) FILTER (side = 0 AND k > coalesce(n, 0))), []) AS chosen_mask,
                   coalesce(flatten(list(mask ORDER BY k) FILTER (side = 1 AND k > coalesce(n, 0))), []) AS rejected_mask
            FROM (SELECT *, '<|im_start|>' || role || chr(10) || text || '<|im_end|>' || chr(10) AS m,
                         CASE WHEN role = 'assistant' THEN [13 + length(role), length(text) + 11] ELSE [24 + length(role) + length(text), 0] END AS mask FROM r) r
            LEFT JOIN shared USING (g) GROUP BY r.g
        )
        SELECT pair_id, CASE WHEN nr = 0 THEN 'chosen_only' WHEN nc = 0 THEN 'rejected_only' WHEN nc = n_shared AND nr = n_shared THEN 'identical' ELSE 'pair' END AS status,
               n_shared, prompt, chosen, rejected, chosen_mask, rejected_mask FROM p""",
    "op4_line_dedup": r"""
        WITH l AS (
            SELECT doc_id, u.pos - 1 AS pos, u.line, trim(u.line, chr(32) || chr(9) || chr(11) || chr(12) || chr(13)) AS plain
            FROM (SELECT doc_id, unnest(list_transform(str_split(text, chr(10)), lambda x, i: {'pos': i, 'line': x})) AS u FROM documents WHERE text IS NOT NULL)
        ), f AS (
            SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY pos) AS k,
                   len(regexp_split_to_array(plain, '[ \t\x0b\x0c\r]+')) AS n FROM l WHERE plain <> ''
        ), same AS (
            SELECT b.doc_id, a.doc_id AS origin, b.k - a.k AS off, b.k, b.pos, b.n, b.k - row_number() OVER (PARTITION BY b.doc_id, a.doc_id, b.k - a.k ORDER BY b.k) AS island
            FROM f a JOIN f b ON a.plain = b.plain AND (a.doc_id < b.doc_id OR a.doc_id = b.doc_id AND a.k < b.k)
        ), runs AS (SELECT DISTINCT doc_id, min(k) AS low, max(k) AS high FROM same GROUP BY doc_id, origin, off, island HAVING sum(n) >= 8
        ), lines AS (SELECT DISTINCT f.doc_id, f.k, f.pos FROM runs JOIN f ON f.doc_id = runs.doc_id AND f.k BETWEEN low AND high
        ), next AS (SELECT *, lead(k) OVER w AS next_k, lead(pos) OVER w AS next_pos FROM lines WINDOW w AS (PARTITION BY doc_id ORDER BY k)
        ), cut AS (SELECT doc_id, unnest(range(pos, CASE WHEN next_k = k + 1 THEN next_pos ELSE pos + 1 END)) AS pos FROM next)
        SELECT d.doc_id, max(coalesce(len(str_split(d.text, chr(10))), 0)) AS n_lines, count(cut.pos) AS n_removed,
               CASE WHEN any_value(d.text) IS NULL THEN NULL ELSE coalesce(string_agg(l.line, chr(10) ORDER BY l.pos) FILTER (cut.pos IS NULL), '') END AS text
        FROM documents d LEFT JOIN l ON d.doc_id = l.doc_id LEFT JOIN cut ON cut.doc_id = l.doc_id AND cut.pos = l.pos GROUP BY d.doc_id""",
    "op7_exact_dedup": r"""
        WITH n AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS t FROM documents)
        SELECT doc_id, min(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size,
               doc_id = min(doc_id) OVER w AS kept, sha256(t) AS text_sha256
        FROM n WINDOW w AS (PARTITION BY t)""",
}
