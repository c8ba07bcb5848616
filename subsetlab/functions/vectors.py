"""Vector expressions (interpreted, for small inputs and SQL) and their Arrow counterparts (for large inputs)."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def norm(v: Column) -> Column:
    return F.sqrt(F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x))


def l2_normalize(v: Column) -> Column:
    """Unit vector; null for the zero vector, null, NaN and infinite input."""
    n = norm(v)
    return F.when((n > 0) & ~F.isnan(n) & (n != float("inf")), F.transform(v, lambda x: x / n))


def rounded(v: Column, digits: int = 6) -> Column:
    """Elements rounded half away from zero; a negative one that rounds to zero stays -0.0, as IEEE rounding has it, where Spark's gives 0.0."""
    return F.transform(v, lambda x: F.when(F.round(x, digits) == 0, x * 0.0).otherwise(F.round(x, digits)))


def cosine(a: Column, b: Column) -> Column:
    return F.try_divide(dot(a, b), norm(a) * norm(b))


def matrix(col: pa.Array, d: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(rows, d) doubles of a list column and the indices of its non-null rows; a wrong length raises."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    valid = np.flatnonzero(np.asarray(col.is_valid()))
    if not len(valid):
        return np.zeros((0, d or 0)), valid
    present = col.drop_null()
    size = np.diff(np.asarray(present.offsets))
    width = d or int(size[0])
    if (size != width).any():
        raise ValueError(f"vectors must have length {width}")
    return np.asarray(present.flatten().to_numpy(zero_copy_only=False), np.float64).reshape(-1, width), valid


def unit_rows(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Unit rows and which rows have one."""
    with np.errstate(over="ignore", invalid="ignore"):
        n = np.sqrt(np.einsum("ij,ij->i", x, x))
        ok = np.isfinite(n) & (n > 0)
        return np.divide(x, np.where(ok, n, 1)[:, None]), ok
