"""Stage I: information filter by Shannon entropy."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import levels as L
from ..functions import udf
from ..schemas import BYTES
from .select import top_n


def h_from_counts(n: Column) -> Column:
    """Aggregate: entropy in nats from the level counts of a group."""
    total = F.sum(n).cast("double")
    return F.greatest(F.lit(0.0), F.ln(total) - F.sum(n * F.ln(n.cast("double"))) / total)


def level_histogram(samples: DataFrame, level: Column) -> DataFrame:
    """(sample_id, level, n, total, prob); samples without levels have no rows. A sample has at most as many rows as there are levels."""
    counts = samples.select("sample_id", F.explode(level).alias("level")).groupBy("sample_id", "level").agg(F.count(F.lit(1)).alias("n"))
    total = counts.withColumn("total", F.sum("n").over(Window.partitionBy("sample_id")))
    return total.withColumn("prob", F.col("n") / F.col("total"))


def sample_entropy(samples: DataFrame, kind: str = BYTES, engine: str = "arrow", levels: int = 16, lo: float | None = -0.5, hi: float | None = 0.5, base: float = math.e, normalized: bool = False) -> DataFrame:
    """(sample_id, entropy). Null and empty payloads have entropy 0.

    The arrow engine is row-local (no exchange); the sql engine explodes levels and counts them, for small inputs.
    normalized divides by the logarithm of the number of levels (256 for bytes).
    """
    if kind == BYTES:
        level, n_levels = L.byte_levels(F.col("payload")), 256
    else:
        level, n_levels = L.quantize_levels(L.doubles(F.col("payload")), levels, lo, hi), levels
    scale = math.log(n_levels) if normalized else math.log(base)
    if engine == "arrow":
        h = udf.byte_entropy("payload") if kind == BYTES else udf.level_entropy(levels)(F.coalesce(level, F.array().cast("array<int>")))
        return samples.select("sample_id", (h / F.lit(scale)).alias("entropy"))
    counts = samples.select("sample_id", F.explode_outer(level).alias("level")).groupBy("sample_id", "level").agg(F.count("level").alias("n"))
    h = counts.groupBy("sample_id").agg(h_from_counts(F.when(F.col("n") > 0, F.col("n"))).alias("h"))
    return h.select("sample_id", (F.coalesce("h", F.lit(0.0)) / F.lit(scale)).alias("entropy"))


def group_entropy(df: DataFrame, keys: list[str], level: str) -> DataFrame:
    """keys and entropy: of a relational histogram, or of a sample whose tiles are rows (counts merge)."""
    counts = df.groupBy(*keys, level).agg(F.count(F.lit(1)).alias("n"))
    return counts.groupBy(*keys).agg(h_from_counts(F.col("n")).alias("entropy"))


def prune_by_threshold(scored: DataFrame, tau: float) -> DataFrame:
    """Rows with entropy below tau go; equality stays."""
    return scored.filter(F.col("entropy") >= tau)


def keep_count(n: int, keep_bp: int) -> int:
    return n * keep_bp // 10_000


def prune_top_fraction(scored: DataFrame, keep_bp: int, n: int | None = None, **plan) -> DataFrame:
    """The floor(keep_bp / 10000 * N) rows of highest entropy; smaller ids first on ties. Nested in keep_bp."""
    n = scored.count() if n is None else n
    return top_n(scored.withColumn("_score", F.round("entropy", 9)), keep_count(n, keep_bp), "_score", "sample_id", **plan).drop("_score")


def entropy_cutoff(scored: DataFrame, keep_bp: int, exact: bool = True) -> float:
    """A threshold that realises the kept share: the lowest kept entropy (exact), or a quantile sketch's value."""
    if exact:
        return prune_top_fraction(scored, keep_bp).agg(F.min("entropy")).first()[0]
    return scored.agg(F.approx_percentile("entropy", 1 - keep_bp / 10_000, 10_000)).first()[0]


def explain_rejects(samples: DataFrame, scored: DataFrame, tau: float) -> DataFrame:
    """(reason, n): empty, constant, low_variation, kept."""
    empty = samples.select("sample_id", (F.coalesce(F.length("payload"), F.lit(0)) == 0).alias("empty"))
    reason = F.when(F.col("empty"), "empty").when(F.round("entropy", 9) == 0, "constant").when(F.col("entropy") < tau, "low_variation").otherwise("kept")
    return scored.join(empty, "sample_id").groupBy(reason.alias("reason")).agg(F.count(F.lit(1)).alias("n"))
