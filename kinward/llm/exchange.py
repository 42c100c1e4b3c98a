"""Packed exchanges: numpy records travel through Spark shuffles as binary blocks.

``deal`` cuts the records of a batch by a hash of their key into (bucket, block) rows. Shuffling
few large rows costs the JVM next to nothing, and a bucket is decoded and sorted in numpy. The
number of buckets follows the size of the input, so a bucket's memory is bounded; what a hot key
would pile up is folded before the shuffle by the caller.
"""

from __future__ import annotations

import math
import os
import tempfile
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def input_bytes(df: DataFrame) -> int:
    """Spark's own estimate of what the plan reads."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def bucket_count(df: DataFrame, per_bucket: int = 4 << 20, least: int = 24) -> int:
    """Buckets in proportion to the input; where Spark knows no size, as many as its shuffles have."""
    size = input_bytes(df)
    if size > 1 << 52:
        return max(least, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    return max(least, math.ceil(size / per_bucket))


def checkpoint_folder(spark: SparkSession) -> None:
    """Use the session's shared checkpoint folder; a local one only where none is named."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isDefined():
        return
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named is None and not sc.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a shared folder on a cluster")
    sc.setCheckpointDir(named or os.path.join(tempfile.gettempdir(), "kinward-checkpoints"))


def cut(df: DataFrame) -> DataFrame:
    """Materialise in the shared folder and cut the lineage."""
    checkpoint_folder(df.sparkSession)
    return df.checkpoint(eager=True)


BATCH_KEY, BATCH_ROWS = "spark.sql.execution.arrow.maxRecordsPerBatch", 1000


def bound_batches(spark: SparkSession) -> str:
    """Send whole texts to Python in batches of BATCH_ROWS at most; returns the setting before."""
    before = spark.conf.get(BATCH_KEY)
    if not 0 < int(before) <= BATCH_ROWS:
        spark.conf.set(BATCH_KEY, str(BATCH_ROWS))
    return before


@contextmanager
def small_batches(spark: SparkSession) -> Iterator[None]:
    """``bound_batches`` for what runs inside."""
    before = bound_batches(spark)
    try:
        yield
    finally:
        spark.conf.set(BATCH_KEY, before)


BLOCK_SCHEMA = "bucket int, block binary"
_BLOCK_ARROW = pa.schema([("bucket", pa.int32()), ("block", pa.binary())])


def deal(records: np.ndarray, key: np.ndarray, buckets: int, beyond: int = 0) -> Iterator[pa.RecordBatch]:
    """(bucket, block) rows of structured records, by the high bits of a mixed uint64 key; buckets are numbered from ``beyond``."""
    if not len(records):
        return
    to = ((key >> np.uint64(24)) % np.uint64(buckets)).astype(np.int32) + np.int32(beyond)
    order = np.argsort(to, kind="stable")
    sent, records = to[order], records[order]
    at = np.append(np.flatnonzero(np.append(True, sent[1:] != sent[:-1])), len(sent))
    yield pa.RecordBatch.from_arrays(
        [pa.array(sent[at[:-1]]), pa.array([packed(records[i:j]) for i, j in zip(at[:-1], at[1:])], pa.binary())],
        schema=_BLOCK_ARROW,
    )


def packed(records: np.ndarray) -> bytes:
    """Bytes of records, transposed so that equal bytes lie together for the shuffle's codec."""
    return records.view(np.uint8).reshape(len(records), records.dtype.itemsize).T.tobytes()


def unpacked(block, dtype: np.dtype) -> np.ndarray:
    cells = np.frombuffer(block, np.uint8).reshape(dtype.itemsize, -1)
    return np.ascontiguousarray(cells.T).view(dtype).ravel()


def per_bucket(
    blocks: DataFrame, dtype: np.dtype, fold: Callable[[np.ndarray], Iterator[pa.RecordBatch]], schema: str, buckets: int,
    beyond: tuple[np.dtype, Callable[[np.ndarray], Iterator[pa.RecordBatch]]] | None = None,
) -> DataFrame:
    """Apply ``fold`` to all records of each bucket; ``beyond`` has the type and the function for those numbered from ``buckets``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        at = None

        def done() -> Iterator[pa.RecordBatch]:
            records = np.concatenate(held)
            held.clear()
            yield from (fold if at < buckets or beyond is None else beyond[1])(records)

        for batch in batches:
            for b, block in zip(batch.column(0).to_pylist(), batch.column(1)):
                if b != at and at is not None:
                    yield from done()
                at = b
                held.append(unpacked(block.as_buffer(), dtype if b < buckets or beyond is None else beyond[0]))
        if at is not None:
            yield from done()

    # a bucket's blocks arrive together; one bucket is in memory at a time
    return (
        blocks.repartition(buckets, "bucket").sortWithinPartitions("bucket").mapInArrow(run, schema)
    )


def reply_batches(doc: np.ndarray, tag: np.ndarray, payload: np.ndarray, kind: int = 0) -> Iterator[pa.RecordBatch]:
    """One (doc_key, doc_tag, kind, block) row per document of records sorted by document."""
    if not len(doc):
        return
    new = np.append(True, (doc[1:] != doc[:-1]) | (tag[1:] != tag[:-1]))
    at = np.append(np.flatnonzero(new), len(doc))
    for lo in range(0, len(at) - 1, 20_000):
        hi = min(lo + 20_000, len(at) - 1)
        yield pa.RecordBatch.from_arrays(
            [
                pa.array(doc[at[lo:hi]]),
                pa.array(tag[at[lo:hi]]),
                pa.array(np.full(hi - lo, kind, np.int32)),
                pa.array([payload[i:j].tobytes() for i, j in zip(at[lo:hi], at[lo + 1 : hi + 1])], pa.binary()),
            ],
            schema=REPLY_ARROW,
        )


REPLY_SCHEMA = "doc_key long, doc_tag int, kind int, block binary"
REPLY_ARROW = pa.schema([("doc_key", pa.int64()), ("doc_tag", pa.int32()), ("kind", pa.int32()), ("block", pa.binary())])


def gathered(replies: DataFrame) -> DataFrame:
    """One row per document with all blocks sent to it."""
    return replies.groupBy("doc_key", "doc_tag").agg(F.collect_list("block").alias("blocks"))


def keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(doc_key, doc_tag, text): the id (null: least value) and a hash of the text.

    Rows that repeat both are one document, stored more than once.
    """
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    return docs.select(
        F.coalesce(F.col(id_col).cast("long"), F.lit(-(2**63))).alias("doc_key"),
        F.hash(text).alias("doc_tag"),
        text.alias("text"),
    )


def id_back(column: str = "doc_key", name: str = "doc_id"):
    """The id column again: the least value stands for null."""
    return F.when(F.col(column) != F.lit(-(2**63)), F.col(column)).alias(name)
