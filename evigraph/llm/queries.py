"""Queries ``opN_*`` over the given tables, with production parameters, and their SQL where SQL can say it."""

from __future__ import annotations

import os
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from pyspark.sql import functions as F

from evigraph.llm import decontamination, embedding_join, jaccard_join, language_id, lattice_lm, line_dedup, mixing, quality, style_tree, url_rules
from evigraph.llm.common import table

Query = Callable[[SparkSession, str], DataFrame]


def vocabulary_path() -> str:
    """The unigram scores come from the public 32k piece vocabulary; EVIGRAPH_PIECES names another."""
    named = os.environ.get("EVIGRAPH_PIECES", "")
    if named:
        return named
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def op1_subword_lattice(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", F.col("lang").alias("class"), (language_id.remainder("doc_id", 7) == 2).alias("held_out"))
    return lattice_lm.scored(docs, lattice_lm.Vocabulary.of(vocabulary_path()))


def op2_site_style_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return style_tree.extracted(table(spark, sf_dir, "pages"))


def op3_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontamination.judged(decontamination.matches(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), ["doc_id"]))


def benchmark_proximity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents with all words of a benchmark window within one word of their place."""
    near = decontamination.matches(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), ["doc_id"], slop=1)
    return near.select("doc_id", "n_words", F.size("items").cast("long").alias("n_items"), F.array_join("items", ",").alias("items"))


def op4_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_rules.judged(table(spark, sf_dir, "pages"), url_rules.labels_of(table(spark, sf_dir, "labels")))


def op5_mixing_to_target_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    columns = ("doc_id", "source", "lang", "topic", "n_tokens", "weight", "probability", "drawn")
    return mixing.mixed(table(spark, sf_dir, "documents").select("doc_id", "source", "lang", "text")).select(*columns)


def op6_rank_order_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = language_id.profiles(docs.filter(language_id.remainder("doc_id", 4) != 2))
    rows = docs.select("doc_id", (language_id.remainder("doc_id", 4) == 2).alias("held_out"), "text")
    return language_id.predicted(rows, model)


def op7_epsilon_grid_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embedding_join.join(table(spark, sf_dir, "embeddings"))


def op8_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "source", "lang", "text")
    return quality.judged(docs, table(spark, sf_dir, "labels")).select("doc_id", "source", "lang", "evidence", "prior", "p_bad", "keep")


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.deduplicated(table(spark, sf_dir, "documents").select("doc_id", "text")).select("doc_id", "n_lines", "n_exact", "n_near", F.col("kept").alias("text"))


def op10_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.join(table(spark, sf_dir, "documents"))


QUERIES: dict[str, Query] = {
    f.__name__: f
    for f in (
        op1_subword_lattice, op2_site_style_tree, op3_benchmark_decontamination, op4_url_rules, op5_mixing_to_target_weights, op6_rank_order_language, op7_epsilon_grid_join,
        op8_quality_classifier, op9_line_dedup, op10_ngram_jaccard_join, benchmark_proximity,
    )
}

_LOWER = "translate({}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

ORACLE_SQL: dict[str, str] = {
    "op3_benchmark_decontamination": rf"""
WITH d AS (SELECT doc_id, coalesce(regexp_extract_all({_LOWER.format("text")}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'), []) AS w FROM documents),
b AS (SELECT item_id, regexp_extract_all({_LOWER.format("text")}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark WHERE text IS NOT NULL AND item_id IS NOT NULL),
win AS (
  SELECT DISTINCT item_id, least(len(w), 13) AS k, list_slice(w, i, i + least(len(w), 13) - 1) AS p
  FROM (SELECT item_id, w, unnest(generate_series(1, greatest(len(w) - 12, 1))) AS i FROM b WHERE len(w) > 0)
),
sizes AS (SELECT DISTINCT k FROM win),
gram AS (
  SELECT doc_id, k, i, list_slice(w, i, i + k - 1) AS p
  FROM (SELECT doc_id, w, k, unnest(generate_series(1, len(w) - k + 1)) AS i FROM d, sizes WHERE len(w) >= k)
),
occ AS (SELECT doc_id, item_id, g.k, i FROM gram g JOIN win ON g.k = win.k AND g.p = win.p),
hit AS (SELECT doc_id, count(DISTINCT pos) AS n_hit FROM (SELECT doc_id, unnest(generate_series(i, i + k - 1)) AS pos FROM occ) GROUP BY doc_id),
items AS (
  SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS ids
  FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS item FROM occ) GROUP BY doc_id
)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
  sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM d LEFT JOIN hit USING (doc_id) LEFT JOIN items USING (doc_id)
""",
}
