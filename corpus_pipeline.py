"""A training-corpus pipeline: five stages over ``documents``, each written as Parquet and read again.

Quality rules, line dedup, MinHash near-dedup, benchmark decontamination, byte-level BPE. Every
stage works on all that the one before kept; all but the last return the columns of documents.

Cases, besides those of the operators: null and empty texts fall to the quality rules, and as input of
a later stage they stay; rows that repeat a document (id and text) are one document to the line
stage, which keeps them all, and one class to the near-copy stage, which keeps one; rows of one id
with unlike texts, and rows without an id, are documents of their own; columns of any other name
pass through all but the last stage (the prefix ``kw_`` is reserved); no documents give no rows, and
an empty benchmark removes nothing.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kinward.llm import byte_bpe, decontaminate, exchange, line_dedup, near_dedup, quality_rules
from kinward.llm.queries import vocabulary_path


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the rules."""
    return quality_rules.keep_passing(docs)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without later copies of lines; n_chars follows the text, emptied ones go."""
    out = line_dedup.dedup_lines(docs, min_run=1)
    left = F.col("text").rlike(r"[^\x20\x09-\x0D]") | (F.col("kw_removed") == 0)
    out = out.filter(F.coalesce(left, F.lit(True)))
    if "n_chars" in docs.columns:
        kind = docs.schema["n_chars"].dataType
        out = out.withColumn("n_chars", F.when(F.col("kw_removed") > 0, F.length("text").cast(kind)).otherwise(F.col("n_chars")))
    return out.select(*[F.col(f"`{c}`") for c in docs.columns])


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near copies."""
    return near_dedup.keep_one(docs)


def benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that no benchmark item is found in."""
    exchange.bound_batches(spark)  # the stage runs when it is written
    return decontaminate.keep_clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of every document left."""
    exchange.bound_batches(spark)
    return byte_bpe.encode_and_digest(docs, vocabulary_path())


STAGES = [
    ("quality_rules", quality),
    ("line_dedup", lines),
    ("near_dedup", near_copies),
    ("decontamination", benchmark),
    ("byte_bpe", tokens),
]

#: SQL has no byte-level BPE; a test holds every stage and run() against plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Apply the stages to documents, through Parquet in the shared folder."""
    exchange.checkpoint_folder(spark)
    base = spark.sparkContext._jsc.sc().getCheckpointDir().get()
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    with exchange.small_batches(spark):  # all stages are written inside, so the session's own setting comes back
        for name, stage in STAGES:
            at = f"{base}/pipeline-{uuid.uuid4().hex}/{name}"
            stage(spark, docs, sf_dir).write.parquet(at)
            docs = spark.read.parquet(at)
    return docs
