"""What the vector searches share: usable vectors, and Arrow lists as matrices."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def usable(rows: DataFrame, id_col: str, vec_col: str, nonzero: bool = False) -> DataFrame:
    """id, vec (array<double>) of rows with an id and a vector free of null, NaN and infinite components."""
    vec = F.col(vec_col).cast("array<double>")
    ok = F.forall(vec, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & (F.size(vec) > 0)
    if nonzero:
        ok &= F.exists(vec, lambda x: x != 0)
    return rows.select(F.col(id_col).cast("long").alias("id"), vec.alias("vec")).where(F.col("id").isNotNull() & F.col("vec").isNotNull() & ok)


def matrix(column: pa.ChunkedArray | pa.Array) -> np.ndarray:
    """Lists of one length as a matrix."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), -1) if len(column) else np.zeros((0, 0))


def best(ids: np.ndarray, scores: np.ndarray, k: int) -> np.ndarray:
    """Places of the k highest scores, ties to smaller ids, highest first."""
    if len(scores) > k:
        among = np.flatnonzero(scores >= np.partition(scores, len(scores) - k)[len(scores) - k])
    else:
        among = np.arange(len(scores))
    return among[np.lexsort((ids[among], -scores[among]))[:k]]


def once(ids: np.ndarray, vec: np.ndarray) -> np.ndarray:
    """Places of the rows, in order, without those that repeat an id and its vector."""
    if len(ids) == len(np.unique(ids)):
        return np.arange(len(ids))
    seen: set[tuple] = set()
    return np.array([i for i in range(len(ids)) if (k := (int(ids[i]), vec[i].tobytes())) not in seen and not seen.add(k)], np.int64)
