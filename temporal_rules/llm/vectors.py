"""Vectors in arrays: which of them count, and their numpy form."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def usable(df: DataFrame, column: str = "embedding"):
    """True for a vector without null or non-finite components that is not zero; never null."""
    x = F.col(column)
    fine = F.forall(x, lambda v: v.isNotNull() & ~F.isnan(v.cast("double")) & (F.abs(v.cast("double")) < float("inf")))
    return F.coalesce(x.isNotNull() & (F.size(x) > 0) & fine & F.exists(x, lambda v: v != 0), F.lit(False))


def widths(df: DataFrame, column: str = "embedding") -> list[int]:
    """The widths of the vectors, of which a table has few; vectors of different widths can't be compared."""
    return sorted(r["d"] for r in df.select(F.size(column).alias("d")).distinct().collect())


def matrix(column: pa.Array | pa.ChunkedArray, width: int) -> np.ndarray:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
        if isinstance(column, pa.ChunkedArray):
            column = column.chunk(0)
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, width)


def sampled(df: DataFrame, key: str, column: str, width: int, rows: int) -> np.ndarray:
    """At most ``rows`` vectors, those of the least hashed keys."""
    got = df.select(key, column).orderBy(F.xxhash64(key), key).limit(rows).select(column).toArrow()
    return matrix(got.column(0), width) if got.num_rows else np.zeros((0, width))
