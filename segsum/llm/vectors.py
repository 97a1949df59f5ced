"""What the two embedding operators share: which vectors take part, and Arrow lists as matrices."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def usable(column: str, dim: int | Column) -> Column:
    """False for vectors that are null, of another length, zero, or hold null or non-finite components."""
    c = F.col(column)
    finite = F.forall(c, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    return F.coalesce((F.size(c) == dim) & finite & F.exists(c, lambda x: x != 0), F.lit(False))


def common_size(rows: DataFrame, column: str) -> int:
    """The most frequent length of usable vectors, the greater one of two; 0 without any."""
    sizes = rows.where(usable(column, F.size(column))).groupBy(F.size(column).alias("size")).agg(F.count(F.lit(1)).alias("n"))
    return sizes.agg(F.max_by("size", F.struct("n", "size"))).first()[0] or 0


def matrix(column: pa.Array, dim: int) -> np.ndarray:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return np.asarray(column.flatten().to_numpy(zero_copy_only=False), dtype=np.float64).reshape(-1, dim)


def stacked(values: list, dim: int) -> np.ndarray:
    return np.stack([np.asarray(v, dtype=np.float64) for v in values]) if len(values) else np.empty((0, dim))
