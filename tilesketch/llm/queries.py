"""Thin queries over the given tables, one for each operator, and the SQL of those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op3_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tilesketch.llm.ngram_join import ngram_components

    return ngram_components(_table(spark, sf_dir, "documents"))


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tilesketch.llm.toxicity import toxicity_scores

    return toxicity_scores(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def op2_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tilesketch.llm.quality import quality_scores

    return quality_scores(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def op4_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tilesketch.llm.sentencepiece_codec import model_bytes
    from tilesketch.llm.token_counts import token_counts

    return token_counts(_table(spark, sf_dir, "documents"), model_bytes())


def op5_chat_perspectives(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tilesketch.llm.chat_format import perspectives

    return perspectives(_table(spark, sf_dir, "conversations"))


def op6_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tilesketch.llm.line_dedup import dedup_lines

    return dedup_lines(_table(spark, sf_dir, "documents").select("doc_id", "text"))


def op7_grid_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tilesketch.llm.grid_join import near_vectors

    return near_vectors(_table(spark, sf_dir, "embeddings"))


def op8_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tilesketch.llm.decontaminate import contaminated

    return contaminated(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def op9_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tilesketch.llm.sentencepiece_codec import encoded, model_bytes

    return encoded(_table(spark, sf_dir, "documents"), model_bytes())


def op10_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tilesketch.llm.personal_data import personal_data

    return personal_data(_table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_toxicity, op2_quality, op3_ngram_jaccard, op4_token_counts, op5_chat_perspectives, op6_line_dedup, op7_grid_join, op8_decontaminate, op9_sentencepiece, op10_personal_data)}


_SHINGLES = r"""
WITH RECURSIVE words AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
shingles AS (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
    ELSE list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i : i + 4], ' ')) END) AS g FROM words),
sizes AS (SELECT doc_id, count(g) AS n FROM words LEFT JOIN shingles USING (doc_id) GROUP BY doc_id),
shared AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM shingles a JOIN shingles b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
linked AS (SELECT x, y FROM shared JOIN sizes p ON p.doc_id = x JOIN sizes q ON q.doc_id = y WHERE 100 * c >= 80 * (p.n + q.n - c)),
edges AS (SELECT x, y FROM linked UNION ALL SELECT y, x FROM linked),
reach(doc_id, top) AS (SELECT doc_id, doc_id FROM documents UNION SELECT y, top FROM reach JOIN edges ON x = reach.doc_id)
SELECT doc_id, n AS n_shingles, min(top) AS component_id FROM reach JOIN sizes USING (doc_id) GROUP BY doc_id, n"""

_LINES = r"""
WITH lines AS (
  SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS i FROM documents WHERE text IS NOT NULL),
full_lines AS (SELECT doc_id, i, regexp_replace(line, '^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$', '', 'g') AS t FROM lines WHERE regexp_matches(line, '[^\x20\x09-\x0D]')),
w AS (SELECT doc_id, i, lead(i) OVER o AS i1, lead(i, 2) OVER o AS i2, t, lead(t) OVER o AS t1, lead(t, 2) OVER o AS t2 FROM full_lines WINDOW o AS (PARTITION BY doc_id ORDER BY i)),
later AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY t, t1, t2 ORDER BY doc_id, i) AS n FROM w WHERE i2 IS NOT NULL) WHERE n > 1),
gone AS (SELECT doc_id, i FROM later UNION SELECT doc_id, i1 FROM later UNION SELECT doc_id, i2 FROM later),
rest AS (SELECT doc_id, string_agg(line, chr(10) ORDER BY i) AS kept FROM lines ANTI JOIN gone USING (doc_id, i) GROUP BY doc_id),
many AS (SELECT doc_id, count(*) AS n FROM gone GROUP BY doc_id)
SELECT d.doc_id, CASE WHEN d.text IS NULL THEN NULL ELSE coalesce(kept, '') END AS text, coalesce(n, 0) AS n_removed_lines
FROM documents d LEFT JOIN rest ON rest.doc_id = d.doc_id LEFT JOIN many ON many.doc_id = d.doc_id"""


def oracle_sql() -> dict[str, str]:
    """SQL for the operators that it can express at test scale; the others are tested against plain versions."""
    return {"op3_ngram_jaccard": _SHINGLES, "op6_line_dedup": _LINES}
