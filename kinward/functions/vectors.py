"""Vector sets as views ``(id BIGINT, vec ARRAY<DOUBLE>)`` and the distance, as SQL and as a kernel.

Integer modes give integer slots, so squared distances are exact and boundaries agree between engines.
"""

from __future__ import annotations

import hashlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from kinward.sources.tables import table

QUERY_STEP = 20
WORDS = 1_000_000  # words whose slots a task remembers


def l2(a: Column, b: Column) -> Column:
    """Euclidean distance of two arrays."""
    squares = F.zip_with(a, b, lambda x, y: (x - y) * (x - y))
    return F.sqrt(F.aggregate(squares, F.lit(0.0), lambda s, x: s + x))


def vectors_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, vec, label) of the embeddings."""
    return table(spark, sf_dir, "embeddings").select(
        F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("vec"), "label"
    )


def hashed_tokens(docs: DataFrame, dim: int) -> DataFrame:
    """(id, vec) of (id, text): signed token counts by hash slot, scaled to length 1000 and rounded.

    Texts are counted where they are read and only counts are shuffled; rows of one id add up.
    """

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codes: dict[str, int] = {}

        def code(word: str) -> int:
            h = int(hashlib.md5(word.encode()).hexdigest()[:7], 16)
            if len(codes) > WORDS:
                codes.clear()
            codes[word] = found = 2 * (h % dim) + (h // dim) % 2
            return found

        for b in batches:
            rows = []
            for text in b.column("text").to_pylist():
                words = Counter((text or "").split(" "))
                at = np.fromiter((codes[w] if w in codes else code(w) for w in words), np.int64, len(words))
                n = np.bincount(at, np.fromiter(words.values(), np.float64, len(words)), 2 * dim)
                rows.append(n[::2] - n[1::2])
            flat = np.concatenate(rows).astype(np.int32) if rows else np.zeros(0, np.int32)
            ends = pa.array(np.arange(len(rows) + 1, dtype=np.int32) * dim)
            yield pa.RecordBatch.from_arrays([b.column("id").cast(pa.int64()), pa.ListArray.from_arrays(ends, pa.array(flat))], ["id", "x"])

    sums = docs.select("id", "text").mapInArrow(count, "id long, x array<int>").groupBy("id").agg(F.collect_list("x").alias("xs"))
    add = lambda a, b: F.when(F.size(a) == 0, b).otherwise(F.zip_with(a, b, lambda x, y: x + y))
    one = F.when(F.size("xs") == 1, F.col("xs")[0]).otherwise(F.aggregate("xs", F.array().cast("array<int>"), add))
    x = sums.select("id", one.alias("x"))
    norm = F.sqrt(F.aggregate("x", F.lit(0).cast("long"), lambda s, v: s + v.cast("long") * v).cast("double"))
    value = lambda v: F.when(F.col("norm") == 0, F.lit(0.0)).otherwise(F.floor(v * 1000.0 / F.col("norm") + 0.5).cast("double"))
    return x.withColumn("norm", norm).select("id", F.transform("x", value).alias("vec"))


def vectors_documents(spark: SparkSession, sf_dir: str, dim: int = 128) -> DataFrame:
    """(id, vec) of the documents' hashed tokens."""
    return hashed_tokens(table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text"), dim)


def vectors_lineitem(spark: SparkSession, sf_dir: str, mode: str = "int") -> DataFrame:
    """(id, vec) of four columns of lineitem; ids are hashes of the row's key."""
    rows = table(spark, sf_dir, "lineitem")
    key = F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    if mode == "int":
        vec = F.array(
            F.floor(F.col("l_quantity") * 20 + 0.5), F.floor(F.col("l_extendedprice") / 100),
            F.floor(F.col("l_discount") * 10000 + 0.5), F.floor(F.col("l_tax") * 10000 + 0.5),
        )
        return rows.select(key.alias("id"), vec.cast("array<double>").alias("vec"))
    cols = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]
    stats = rows.agg(*[f(c).alias(f"{p}_{c}") for c in cols for p, f in (("m", F.avg), ("s", F.stddev_pop))])
    wide = rows.crossJoin(F.broadcast(stats))  # one row
    return wide.select(key.alias("id"), F.array(*[(F.col(c) - F.col(f"m_{c}")) / F.col(f"s_{c}") for c in cols]).alias("vec"))


def vectors_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, vec) of size and price of parts; many ties."""
    return table(spark, sf_dir, "part").select(
        F.col("p_partkey").cast("long").alias("id"),
        F.array(F.col("p_size") * 20.0, F.floor(F.col("p_retailprice") * 10 + 0.5).cast("double")).cast("array<double>").alias("vec"),
    )


def split_base_queries(points: DataFrame, step: int = QUERY_STEP) -> tuple[DataFrame, DataFrame]:
    """All rows, and as queries those whose id is divisible by ``step``."""
    queries = points.filter(F.col("id") % step == 0).select(F.col("id").alias("qid"), "vec")
    return points.select("id", "vec"), queries


def checked(points: DataFrame, name: str = "points") -> int:
    """Dimension of a vector set; raises on null or uneven vectors, null slots or NaN, and repeated ids."""
    id_col = "qid" if "qid" in points.columns else "id"
    bad_slot = F.exists("vec", lambda x: x.isNull() | F.isnan(x))
    row = points.agg(
        F.count(F.lit(1)).alias("n"), F.count_distinct(id_col).alias("ids"), F.min(F.size("vec")).alias("lo"), F.max(F.size("vec")).alias("hi"),
        F.count_if(F.col("vec").isNull() | F.col(id_col).isNull() | F.coalesce(bad_slot, F.lit(True))).alias("bad"),
    ).first()
    if row.bad:
        raise ValueError(f"{name}: {row.bad} rows hold a null, a null slot or NaN")
    if row.n and row.lo != row.hi:
        raise ValueError(f"{name}: vectors of {row.lo} to {row.hi} slots")
    if row.ids != row.n:
        raise ValueError(f"{name}: {row.n - row.ids} repeated ids")
    return row.hi or 0


def matrix(column) -> np.ndarray:
    """2-d float64 array of a column of lists (pandas or Arrow)."""
    if hasattr(column, "flatten") and hasattr(column, "offsets"):
        flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
        return flat.reshape(len(column), -1) if len(column) else np.zeros((0, 0))
    return np.stack(column.to_numpy()).astype(np.float64) if len(column) else np.zeros((0, 0))


def squared(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """All squared distances in expanded form, clamped at zero; compare with ``direct`` near a boundary."""
    out = (a * a).sum(1)[:, None] + (b * b).sum(1)[None, :] - 2 * (a @ b.T)
    return np.maximum(out, 0, out=out)


def direct(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Distances of paired rows, without cancellation."""
    d = a - b
    return np.sqrt(np.einsum("ij,ij->i", d, d))


def slack(a: np.ndarray, b: np.ndarray) -> float:
    """Bound on the error of ``squared``."""
    return 1e-12 * float((a * a).sum(1).max(initial=0) + (b * b).sum(1).max(initial=0)) * max(1, a.shape[1]) + 1e-300


def nearest(qid, q: np.ndarray, ids, p: np.ndarray, k: int, drop_self: bool = False):
    """(row of q, row of p, distance), k a query, ordered by distance then id; exact also at ties."""
    if not len(q) or not len(p):
        return np.zeros(0, int), np.zeros(0, int), np.zeros(0)
    d2 = squared(q, p)
    want = min(k + (1 if drop_self else 0), len(p))
    edge = np.partition(d2, want - 1, axis=1)[:, want - 1] if want < len(p) else d2.max(axis=1)
    i, j = np.nonzero(d2 <= (edge + slack(q, p))[:, None])
    if drop_self:
        other = ids[j] != qid[i]
        i, j = i[other], j[other]
    d = direct(q[i], p[j])
    order = np.lexsort((ids[j], d, i))
    i, j, d = i[order], j[order], d[order]
    at = np.searchsorted(i, np.arange(len(q)))
    rank = np.arange(len(i)) - at[i]
    keep = rank < k
    return i[keep], j[keep], d[keep]
