"""Vector helpers: usable rows, Arrow lists to matrices, and the per-query top-k merge."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def usable(rows: DataFrame, key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """``(key long, v array<double>)`` of rows with a key and a non-empty vector of finite components only."""
    v = F.col(vector).cast("array<double>")
    finite = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    return rows.where(F.col(key).isNotNull() & F.col(vector).isNotNull() & (F.size(vector) > 0)).where(finite).select(F.col(key).cast("long").alias("vec_id"), v.alias("v"))


def query_rows(vectors: DataFrame, every: int) -> DataFrame:
    """The stated query set: ids divisible by ``every``; of rows that repeat an id one vector (the smallest) is asked for."""
    return vectors.where(F.col("vec_id") % every == 0).groupBy("vec_id").agg(F.min("v").alias("v"))


def matrix(column: pa.Array | pa.ChunkedArray, dtype=np.float64) -> np.ndarray:
    """Rows of an Arrow list column as a matrix; shorter vectors are padded with zeros."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    lengths = np.asarray(column.value_lengths(), dtype=np.int64)
    flat = np.asarray(column.flatten(), dtype=dtype)
    if len(lengths) == 0:
        return np.zeros((0, 0), dtype)
    if (lengths == lengths[0]).all():
        return flat.reshape(len(lengths), lengths[0])
    out = np.zeros((len(lengths), lengths.max()), dtype)
    out[np.arange(lengths.max()) < lengths[:, None]] = flat
    return out


def widen(a: np.ndarray, width: int) -> np.ndarray:
    return a if a.shape[1] == width else np.pad(a, ((0, 0), (0, width - a.shape[1])))


def merge_top(found: DataFrame, k: int) -> DataFrame:
    """The ``k`` best of the tiles' own best: ``query_id, rank, vec_id, score``; ties to the smaller id."""
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
