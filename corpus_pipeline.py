"""Corpus pipeline over ``documents``: quality, line duplicates, near duplicates, benchmark leaks, tokens.

Each stage works on everything that its predecessor kept.  All but the last return the columns of their input:

* ``quality`` drops the documents that the quality discriminant rejects (score under 0.3);
* ``lines`` removes lines of later occurrences of repeated three-line windows; a document of which nothing but blank lines
  is left by that goes, every other one stays, and ``n_chars`` follows the text;
* ``near_duplicates`` keeps of each component of near-equal documents the one with the smallest ``doc_id``;
* ``decontaminate`` drops the documents that hold a benchmark item, also with other names and numbers;
* ``tokens`` encodes the texts with the SentencePiece model and checks that they decode.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tilesketch.llm import decontaminate as leaks
from tilesketch.llm import line_dedup, ngram_join, quality, sentencepiece_codec
from tilesketch.llm.scratch import drop, keep


def _without(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """``docs`` but for the rows with one of the ids."""
    gone = ids.select(F.col("doc_id").cast("long").alias("__gone")).distinct()
    return docs.join(gone.hint("shuffle_hash"), docs["doc_id"].cast("long") == F.col("__gone"), "left_anti")


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = quality.fit_on_labels(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"), "quality")  # of 200,000 labelled rows at most
    return quality.accepted(docs, model, least=0.3)


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    out = line_dedup.dedup_lines(docs)
    emptied = (F.col("n_removed_lines") > 0) & ~F.coalesce(F.col("text"), F.lit("")).rlike(r"[^\x20\x09-\x0D]")
    out = out.where(~emptied)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("n_removed_lines") > 0, F.length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))
    return out.select(*docs.columns)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return _without(docs, ngram_join.ngram_components(docs).where("doc_id <> component_id"))


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return _without(docs, leaks.contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")))


def token_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return sentencepiece_codec.encoded(docs, sentencepiece_codec.model_bytes())


STAGES = [("quality", quality_stage), ("lines", line_stage), ("near_duplicates", near_duplicate_stage), ("decontaminate", decontamination_stage), ("tokens", token_stage)]

#: SQL has neither the discriminant nor the codec; the tests hold each stage against a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows of the last stage, from the table ``documents``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for i, (_, stage) in enumerate(STAGES):
        before, docs = docs, stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = keep(docs)
            drop(before)  # removes what ``keep`` wrote, never an input
    return docs
