"""The corpus pipeline: five stages from raw documents to token ids."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trainscape.llm import language_id, mixing, near_dedup, secret_scan, sentencepiece_fst
from trainscape.llm._common import checkpointed, forget, small_side

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
#: Bytes of texts that a task hands to Python at once; the session keeps it, as a stage's rows are computed when they are written.
BATCH_BYTES = 4 << 20


def bounded(spark: SparkSession, rows: DataFrame) -> DataFrame:
    """The rows, whose Arrow batches hold at most about BATCH_BYTES instead of 10,000 texts of any length."""
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))
    return rows


def identified(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in a learnt language, lang set to it; texts without letters go, and all if no language can be learnt."""
    prototypes = language_id.learn_prototypes(language_id.train_rows(bounded(spark, docs)))
    return language_id.with_language(docs.select(*COLUMNS), prototypes)


def deduplicated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, that of the smallest doc_id, of each group of near duplicates."""
    groups = near_dedup.near_dedup(bounded(spark, docs), width=5, percent=80)
    dropped = checkpointed(groups.where(~F.col("kept")).select(F.col("doc_id").alias("dropped_id")).distinct())
    return docs.join(small_side(dropped), F.col("doc_id") == F.col("dropped_id"), "left_anti").select(*COLUMNS)


def without_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents; secrets in their texts are replaced by their kinds, n_chars follows."""
    return secret_scan.redact_secrets(bounded(spark, docs).select(*COLUMNS)).withColumn("n_chars", F.length("text").cast("long"))


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents as often as the mix of sources takes them: not at all, once or twice."""
    return mixing.repeat_taken(docs.select(*COLUMNS))


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids and round_trip of each document."""
    return sentencepiece_fst.encode_pieces(bounded(spark, docs))


STAGES = [("language_id", identified), ("near_dedup", deduplicated), ("secret_scan", without_secrets), ("mix_sources", mixed), ("sentencepiece", encoded)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Applies the stages to documents; each result is written to the shared folder as Parquet and read again, the one before it is deleted.

    An empty table gives an empty result; null and empty texts go in the first
    stage, repeated rows in none but the near-duplicate stage keeps all rows of
    a kept doc_id; rows without doc_id stay alone. Columns beyond those of
    documents are ignored.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    before = None
    for _, stage in STAGES:
        docs = checkpointed(stage(spark, docs, sf_dir))
        if before is not None:
            forget(before)
        before = docs
    return docs


#: Language models and token paths are beyond SQL; the stages are tested against brute force.
ORACLE_SQL = None
