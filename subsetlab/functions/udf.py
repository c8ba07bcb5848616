"""Arrow functions: entropy of bytes and level arrays, grouped entropy, table functions, SQL registration."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, IntegerType, LongType, StructField, StructType

BLOCK = 1 << 19
DOUBLE = DoubleType()  # as an object: workers import this module without a session


def counts_entropy(counts: np.ndarray) -> np.ndarray:
    """Entropy in nats of every row of counts; ln n - sum(c ln c) / n, so a constant sample gives +0.0; empty rows give 0."""
    n = counts.sum(axis=1)
    c = counts.astype(np.float64)
    part = (c * np.log(np.where(c > 0, c, 1))).sum(axis=1)
    full = np.maximum(n, 1)
    return np.maximum(0.0, np.log(full) - part / full)


def bytes_entropy(data: np.ndarray, offs: np.ndarray) -> np.ndarray:
    """Entropy over the 256 byte levels of every row."""
    out, i, n = np.zeros(len(offs) - 1), 0, len(offs) - 1
    while i < n:
        j = max(i + 1, min(int(np.searchsorted(offs, offs[i] + BLOCK, "right")) - 1, i + 2048))
        rows = np.repeat(np.arange(j - i), np.diff(offs[i : j + 1]))
        flat = np.bincount(rows * 256 + data[offs[i] : offs[j]], minlength=(j - i) * 256)
        out[i:j] = counts_entropy(flat.reshape(j - i, 256))
        i = j
    return out


def _buffers(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    if pa.types.is_string(col.type) or pa.types.is_large_string(col.type):
        col = col.cast(pa.large_binary())
    else:
        col = col.cast(pa.large_binary())
    if col.null_count:
        col = col.fill_null(b"")
    bufs = col.buffers()
    offs = np.frombuffer(bufs[1], np.int64)[col.offset : col.offset + len(col) + 1] if len(col) else np.zeros(1, np.int64)
    data = np.frombuffer(bufs[2], np.uint8) if bufs[2] is not None else np.zeros(0, np.uint8)
    return data[offs[0] : offs[-1]], offs - offs[0]


@F.arrow_udf(DOUBLE)
def byte_entropy(payload: pa.Array) -> pa.Array:
    return pa.array(bytes_entropy(*_buffers(payload)))


def level_entropy(levels: int):
    """Arrow function for arrays of levels 0 .. levels-1."""

    @F.arrow_udf(DOUBLE)
    def run(col: pa.Array) -> pa.Array:
        size = np.diff(np.asarray(col.offsets)) if col.null_count == 0 else np.array([len(x) if x.is_valid else 0 for x in col])
        flat = np.asarray(col.flatten())
        rows = np.repeat(np.arange(len(col)), size)
        return pa.array(counts_entropy(np.bincount(rows * levels + flat, minlength=len(col) * levels).reshape(len(col), levels)))

    return run


@F.pandas_udf(DOUBLE)
def entropy_of_group(levels: pd.Series) -> float:
    """Entropy of the values of a group (grouped aggregate)."""
    return float(counts_entropy(levels.value_counts().to_numpy()[None, :])[0]) if len(levels) else 0.0


@F.udtf(returnType=StructType([StructField("level", IntegerType()), StructField("n", LongType())]))
class ByteLevels:
    """levels(text): a row for every byte level that occurs."""

    def eval(self, text: str) -> Iterator[Row]:
        counts = np.bincount(np.frombuffer((text or "").encode(), np.uint8), minlength=256)
        for level in np.flatnonzero(counts).tolist():
            yield level, int(counts[level])


@F.arrow_udf(DOUBLE)
def cosine_arrow(a: pa.Array, b: pa.Array) -> pa.Array:
    from .vectors import matrix, unit_rows

    x, _ = matrix(a)
    y, _ = matrix(b)
    return pa.array(np.einsum("ij,ij->i", unit_rows(x)[0], unit_rows(y)[0]))


def register(spark: SparkSession) -> None:
    """sl_entropy(text), sl_cosine(a, b), sl_group_entropy(levels) and the table function sl_levels(text) for SQL."""
    spark.udf.register("sl_entropy", byte_entropy)
    spark.udf.register("sl_cosine", cosine_arrow)
    spark.udf.register("sl_group_entropy", entropy_of_group)
    spark.udtf.register("sl_levels", ByteLevels)
