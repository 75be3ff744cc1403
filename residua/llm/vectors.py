"""What the two vector operators share: which vectors take part, and Arrow list columns as matrices."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def usable(vec: Column) -> Column:
    """Not null, not empty, no null or non-finite component, not all zero."""
    finite = lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))
    return F.coalesce(vec.isNotNull() & (F.size(vec) > 0) & F.forall(vec, lambda x: F.coalesce(finite(x), F.lit(False))) & F.exists(vec, lambda x: x != 0), F.lit(False))


def width(rows: DataFrame, vec: str) -> int:
    """The most common length of the usable vectors (the least one among equals); others take no part."""
    counts = rows.groupBy(F.size(vec).alias("d")).agg(F.count(F.lit(1)).alias("n"))
    return (counts.agg(F.min_by("d", F.struct(-F.col("n"), "d")).alias("d")).first() or [None])[0] or 0


def matrix(column: pa.Array) -> np.ndarray:
    """Vectors of one length as rows, in double precision."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1)


def sample(rows: DataFrame, vec: str, most: int) -> np.ndarray:
    """At most ``most`` vectors, those of the least hashes: the bounded sample that an index is fitted on."""
    got = rows.select(vec).orderBy(F.xxhash64(vec)).limit(most).toArrow().column(0)
    return matrix(got)
