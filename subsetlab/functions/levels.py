"""Intensity levels as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

LUMA = (0.299, 0.587, 0.114)


def doubles(vec: Column) -> Column:
    return F.transform(vec, lambda x: x.cast("double"))


def to_gray(bands: Column, weights: tuple[float, ...]) -> Column:
    """One intensity per pixel from an array of bands (each an array of pixels): the weighted sum."""
    out = F.transform(bands[0], lambda x: x * F.lit(float(weights[0])))
    for k, w in enumerate(weights[1:], 1):
        out = F.zip_with(out, bands[k], lambda a, b: a + b * F.lit(float(w)))  # noqa: B023
    return out


def equal_weights(n: int) -> tuple[float, ...]:
    return tuple(1.0 / n for _ in range(n))


def cut_bands(vec: Column, n: int, width: int) -> Column:
    """A flat vector as n bands of width pixels."""
    return F.array(*[F.slice(vec, k * width + 1, width) for k in range(n)])


def byte_levels(payload: Column) -> Column:
    """Levels of a string's UTF-8 bytes, as two-digit hex strings."""
    return F.regexp_extract_all(F.hex(F.encode(payload, "UTF-8")), F.lit(".."), F.lit(0))


def quantize_levels(vec: Column, levels: int, lo: float | None = None, hi: float | None = None) -> Column:
    """Levels 0 .. levels-1 over the fixed range lo to hi (clamped), or over each sample's own range where lo is None.

    A sample with a null, NaN or infinite element has no levels (null), as it has no unit vector.
    """
    low = F.array_min(vec) if lo is None else F.lit(float(lo))
    high = F.array_max(vec) if hi is None else F.lit(float(hi))
    step = lambda x: F.coalesce(F.floor(F.try_divide(x - low, high - low) * levels), F.lit(0)).cast("int")
    broken = F.exists(vec, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return F.when(~broken, F.transform(vec, lambda x: F.greatest(F.lit(0), F.least(F.lit(levels - 1), step(x)))))
