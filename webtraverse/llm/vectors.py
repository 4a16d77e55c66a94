"""What the vector operators share: which vectors take part, and streams of groups that hold data first and queries after."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def usable(embedding: Column) -> Column:
    """Neither null, empty or zero, nor holding null, NaN or infinite components."""
    finite = F.forall(embedding, lambda x: F.coalesce(~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))), F.lit(False)))
    return F.coalesce(embedding.isNotNull() & finite & F.exists(embedding, lambda x: x != 0), F.lit(False))


def matrix(column: pa.Array, rows: np.ndarray | None = None) -> np.ndarray:
    """Rows of equal length from a list column, in double precision."""
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1) if len(column) else flat.reshape(0, 0)


def grouped_stream(batches, key: str):
    """(key, batch) slices of a stream sorted by ``key``: a group may come in several slices."""
    for batch in batches:
        if not batch.num_rows:
            continue
        keys = batch.column(batch.schema.get_field_index(key)).to_numpy(zero_copy_only=False)
        edges = [0, *(np.flatnonzero(keys[1:] != keys[:-1]) + 1).tolist(), len(keys)]
        for a, b in zip(edges[:-1], edges[1:]):
            yield keys[a], batch.slice(a, b - a)


def by_group(df: DataFrame, key: str = "key") -> DataFrame:
    """All rows of a key in one task, data (role 0) before queries (role 1)."""
    return df.repartition(key).sortWithinPartitions(key, "role")
