"""Encoders: payload to vector. A frozen model plugs in through Encoder and encode(); the others stand in for one."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from typing import Protocol

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import levels as L
from ..functions import vectors as V

DIM = 64


class Encoder(Protocol):
    """A frozen model: payloads of one batch in, one row of size numbers for each out. It travels with the task's function, which Spark broadcasts if large.

    A row of NaN stands for a payload that has no vector.
    """

    size: int

    def __call__(self, payloads: pa.Array) -> np.ndarray: ...


def encode(samples: DataFrame, encoder: Encoder) -> DataFrame:
    """(sample_id, vec) by any frozen encoder, batch by batch in a map-only pass; null payloads and rows of NaN have a null vector."""
    size = encoder.size

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = np.asarray(encoder(batch.column(1)), np.float64)
            if out.shape != (batch.num_rows, size):
                raise ValueError(f"the encoder gave {out.shape}, not {(batch.num_rows, size)}")
            none = np.isnan(out).any(axis=1) | np.asarray(batch.column(1).is_null())
            vec = pa.ListArray.from_arrays(pa.array(np.arange(len(out) + 1, dtype=np.int32) * size), pa.array(out.ravel()), mask=pa.array(none))
            yield pa.RecordBatch.from_arrays([batch.column(0), vec], ["sample_id", "vec"])

    return samples.select("sample_id", "payload").mapInArrow(run, "sample_id long, vec array<double>")


def identity(samples: DataFrame) -> DataFrame:
    """(sample_id, vec): the payload is the vector."""
    return samples.select("sample_id", L.doubles(F.col("payload")).alias("vec"))


def hashed_tokens(samples: DataFrame, dim: int = DIM, engine: str = "arrow") -> DataFrame:
    """(sample_id, vec): lower-cased blank-separated tokens, bucket = first 32 bits of MD5 modulo dim, square root of counts, unit length.

    Texts without tokens have a null vector.
    """
    if engine == "sql":
        token = F.explode(F.split(F.lower("payload"), r"\s+"))
        buckets = samples.select("sample_id", token.alias("t")).filter("t <> ''").select("sample_id", (F.conv(F.substring(F.md5("t"), 1, 8), 16, 10).cast("long") % dim).cast("int").alias("b"))
        counts = buckets.groupBy("sample_id", "b").agg(F.sqrt(F.count(F.lit(1)).cast("double")).alias("c"))
        maps = counts.groupBy("sample_id").agg(F.map_from_entries(F.collect_list(F.struct("b", "c"))).alias("m"))  # dim entries at most
        vec = F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0.0)))
        return samples.select("sample_id").join(maps.select("sample_id", V.l2_normalize(vec).alias("vec")), "sample_id", "left")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[str, int] = {}
        for batch in batches:
            out = np.zeros((batch.num_rows, dim))
            for row, text in enumerate(batch.column(1).to_pylist()):
                for t in (text or "").lower().split():
                    b = known.get(t)
                    if b is None:
                        if len(known) > 500_000:
                            known.clear()
                        b = known[t] = int(hashlib.md5(t.encode()).hexdigest()[:8], 16) % dim
                    out[row, b] += 1
            unit, ok = V.unit_rows(np.sqrt(out))
            vec = pa.ListArray.from_arrays(pa.array(np.arange(len(unit) + 1, dtype=np.int32) * dim), pa.array(unit.ravel()), mask=pa.array(~ok))
            yield pa.RecordBatch.from_arrays([batch.column(0), vec], ["sample_id", "vec"])

    return samples.select("sample_id", "payload").mapInArrow(run, "sample_id long, vec array<double>")


def level_profile(samples: DataFrame, levels: int = 16, lo: float = -0.5, hi: float = 0.5) -> DataFrame:
    """(sample_id, vec): share of each level."""
    level = L.quantize_levels(L.doubles(F.col("payload")), levels, lo, hi)
    share = lambda k: F.size(F.filter("lv", lambda x: x == k)) / F.size("lv")
    return samples.select("sample_id", level.alias("lv")).select("sample_id", F.array(*[share(k) for k in range(levels)]).alias("vec"))


def normalized(vectors: DataFrame) -> DataFrame:
    """(sample_id, vec) with unit vectors; rows without one keep a null vector."""
    return vectors.withColumn("vec", V.l2_normalize(F.col("vec")))


def random_projection(vectors: DataFrame, d_in: int, d_out: int, seed: int = 42) -> DataFrame:
    """(sample_id, vec) in d_out dimensions by signs from MD5, for cheaper clustering; renormalise afterwards."""
    sign = lambda i, j: 1.0 if int(hashlib.md5(f"{seed}:{i}:{j}".encode()).hexdigest()[:8], 16) % 2 else -1.0
    m = np.array([[sign(i, j) for j in range(d_out)] for i in range(d_in)]) / np.sqrt(d_out)

    @F.arrow_udf("array<double>")
    def project(vec: pa.Array) -> pa.Array:
        x, valid = V.matrix(vec, d_in)
        rows = [None] * len(vec)
        for k, r in zip(valid.tolist(), (x @ m).tolist(), strict=True):
            rows[k] = r
        return pa.array(rows, pa.list_(pa.float64()))

    return vectors.withColumn("vec", project("vec"))
