"""Readers of the given tables with explicit schemas, and round trips through other formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

# The schemas of the given tables.
SCHEMAS = {
    "embeddings": "vec_id BIGINT, embedding ARRAY<FLOAT>, label INT",
    "documents": "doc_id BIGINT, text STRING, lang STRING, source STRING, n_chars BIGINT",
    "benchmark": "item_id BIGINT, text STRING",
    "labels": "doc_id BIGINT, quality INT, toxic INT",
    "pages": "page_id BIGINT, url STRING, html STRING",
    "conversations": "conv_id BIGINT, turn BIGINT, role STRING, text STRING",
}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table of the directory; a declared schema spares the look into the files."""
    reader = spark.read
    if name in SCHEMAS:
        reader = reader.schema(SCHEMAS[name])
    return reader.parquet(f"{sf_dir}/{name}.parquet")


def round_trip(df: DataFrame, path: str, kind: str) -> DataFrame:
    """Write as JSON or CSV and read back with the same schema."""
    df.write.mode("overwrite").option("header", True).format(kind).save(path)
    return df.sparkSession.read.schema(df.schema).option("header", True).format(kind).load(path)
