"""The training-corpus pipeline: quality rules, line dedup, near duplicates, mixing, encoding.

run() writes each stage's rows as Parquet in the shared checkpoint folder and reads them back as the next stage's
documents, so no stage is computed twice and a lost executor costs only the tasks of the stage at hand. A stage's folder
goes when the next one is written; the last one stays, as the returned rows are read from it.

Every stage takes documents with null, empty and very long texts, null ids, languages and sources, repeated rows and
further columns of any name, and an empty table; all but the last return the columns they were given.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common, line_dedup, mixing, near_dups, pieces, quality


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that fail the base rules or lie outside their group's thresholds go; null and empty texts have no words and go. Repeated rows are judged each."""
    return quality.keep_good(docs)


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines found in ten documents or more go; n_chars follows the text. A null text is one empty line and comes out empty; rows of equal doc_id count as one document."""
    out = line_dedup.dedup_lines(docs)
    if "n_chars" not in docs.columns:
        return out
    return out.select(*[F.length("text").cast("long").alias(c) if c == "n_chars" else F.col(f"`{c}`") for c in out.columns])


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates stays, the one of least doc_id (null last), and one of equal rows; documents without words all stay."""
    return near_dups.drop_near_duplicates(docs)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix of sources takes it, from never to twice; a text without words is never taken. A null source is one of its own."""
    return mixing.mix(docs)


def encoding_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, lang, source, n_tokens, ids, round_trip), a row for each row; null for a null text, no ids for an empty one."""
    return pieces.encode_texts(docs.select("doc_id", "lang", "source", "text"), check=True).drop("text")


STAGES = [("quality", quality_stage), ("lines", line_stage), ("near_duplicates", near_duplicate_stage), ("mixing", mixing_stage), ("encoding", encoding_stage)]

#: Quantile sketches, drawn copies and piece ids have no SQL; tests/llm holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = common.shared_folder(spark, "pipeline")
    docs, before = common.table(spark, sf_dir, "documents"), None
    for name, stage in STAGES[:-1]:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
        if before:
            common.remove_folder(spark, before)
        before = f"{folder}/{name}"
    return STAGES[-1][1](spark, docs, sf_dir)
