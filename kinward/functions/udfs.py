"""The UDF surface: vectorised distance, grouped top-k, a table function, and registration for SQL."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.DoubleType())
def l2_udf(a: pd.Series, b: pd.Series) -> pd.Series:
    """Distance of two array columns."""
    if not len(a):
        return pd.Series([], dtype=float)
    x, y = np.stack(a.to_numpy()).astype(float), np.stack(b.to_numpy()).astype(float)
    return pd.Series(np.sqrt(((x - y) ** 2).sum(axis=1)))


@F.pandas_udf(T.ArrayType(T.LongType()))
def topk_ids(dist: pd.Series, ids: pd.Series, k: pd.Series) -> np.ndarray:
    """Ids of the k least distances of a group, ties by id."""
    order = np.lexsort((ids.to_numpy(), dist.to_numpy()))[: int(k.iloc[0])]
    return ids.to_numpy()[order].tolist()


SMALL_INDEX = 64 << 20


def rknn_function(points: DataFrame, radii: DataFrame):
    """A table function ``rknn(qid, vec, k)`` over a small index, which its code carries (checked: 64 MB)."""
    schema = T.StructType([T.StructField("qid", T.LongType()), T.StructField("id", T.LongType()), T.StructField("dist", T.DoubleType())])
    held = points.select("id", "vec").join(radii, "id")
    size = held.agg(F.sum((F.size("vec") + F.size("r")) * 8)).first()[0] or 0
    if size > SMALL_INDEX:
        raise ValueError("the index is too large for a table function; use HybridIndex.search")
    rows = held.orderBy("id").toPandas()
    ids, x, r = rows["id"].to_numpy(), np.stack(rows["vec"].to_numpy()), [np.asarray(v) for v in rows["r"]]

    class Rknn:
        def eval(self, qid: int, vec: list, k: int):
            d = np.sqrt(((x - np.asarray(vec, float)) ** 2).sum(axis=1))
            for i in range(len(ids)):
                if ids[i] != qid and d[i] <= r[i][k - 1] * (1 + 1e-12):
                    yield int(qid), int(ids[i]), float(d[i])

    return F.udtf(Rknn, returnType=schema)


def register_all(spark: SparkSession, index: tuple[DataFrame, DataFrame] | None = None) -> None:
    """Make the functions known to SQL; ``index`` is (points, radii) of a small index."""
    spark.udf.register("l2_udf", l2_udf)
    spark.udf.register("topk_ids", topk_ids)
    if index:
        spark.udtf.register("rknn", rknn_function(*index))
