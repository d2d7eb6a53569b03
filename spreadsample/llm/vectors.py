"""What the vector operators share: which vectors take part, and their numpy form."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def usable(vector: Column) -> Column:
    """True for vectors without null or non-finite components and with one that is not zero."""
    finite = lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))
    return F.coalesce(F.forall(vector, finite) & F.exists(vector, lambda x: x != 0), F.lit(False))


def dimension(vectors: DataFrame, column: str) -> int:
    """The commonest length among the vectors (the smaller at a tie), 0 if there are none."""
    sizes = vectors.groupBy(F.size(column).alias("d")).count().orderBy(F.desc("count"), "d").first()
    return sizes[0] if sizes else 0


def by_share(rows: DataFrame, key: Column, want: int, total: int) -> DataFrame:
    """About `want` of `total` rows, by a hash of their key: chosen where they are read, so no task sends more than its share."""
    return rows if want >= total else rows.where(F.pmod(F.xxhash64(key, F.lit(11)), F.lit(1 << 30)) < F.lit(int((1 << 30) * want / total)))


def matrix(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    """Rows of a list column of equal lengths, in double precision."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    n = len(column)
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(n, -1) if n else flat.reshape(0, 0)
