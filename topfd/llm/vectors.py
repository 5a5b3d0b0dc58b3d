"""Vector tables for the two searches: usable rows, copies as one class, blocks of bounded size."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def finite(vec: str = "embedding"):
    """Not null, not empty, and every component a finite number."""
    return F.col(vec).isNotNull() & (F.size(vec) > 0) & F.forall(vec, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x.cast("double")) < F.lit(float("inf"))))


def smallest_ids(rows: DataFrame, k: int) -> DataFrame:
    """rows(vec_id, vec) -> vec, ids: distinct vectors, each with its k + 1 smallest ids. As ties go to the smaller id and a query leaves out
    itself alone, no further copy can be among any query's k nearest; so this loses nothing, and a vector that a third of all
    rows hold is one row. Copies are dealt to 4,096 parts first, and only k + 1 ids of a part go on."""
    part = rows.groupBy("vec", F.pmod(F.xxhash64("vec_id"), F.lit(4096)).alias("salt")).agg(F.slice(F.array_sort(F.collect_set("vec_id")), 1, k + 1).alias("ids"))
    return part.groupBy("vec").agg(F.slice(F.array_sort(F.array_distinct(F.flatten(F.collect_list("ids")))), 1, k + 1).alias("ids"))


def matrix(column: pa.Array, dtype: type = np.float64) -> np.ndarray:
    """Rows of a list column, shorter ones filled with zeros."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    sizes = column.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(dtype)
    width = int(sizes.max(initial=0))
    if (sizes == width).all():
        return flat.reshape(len(sizes), width)
    out = np.zeros((len(sizes), width), dtype)
    out[np.arange(width)[None, :] < sizes[:, None]] = flat
    return out
