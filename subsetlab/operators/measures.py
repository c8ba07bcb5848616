"""Cost and accuracy measures. Image generators are not trained here: the distances are proxies on features, not the published scores."""

from __future__ import annotations

import math
import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import vectors as V
from ..sources.tables import stage
from .pairs import best_similarity, nearest_rows, similar_rows
from .sampling import hash_order
from .select import DEFAULT, SelectionPlanner, group_median, rank_in_group


def moments(vectors: DataFrame, *by: str) -> DataFrame:
    """by, pos, mu, sd (population): one row for each vector position."""
    long = vectors.select(*by, F.posexplode("vec").alias("pos", "x"))
    return long.groupBy(*by, "pos").agg(F.avg("x").alias("mu"), F.stddev_pop("x").alias("sd"))


def moment_distance(selected: DataFrame, test: DataFrame, *by: str) -> DataFrame:
    """by, mean_part, spread_part, moment: squared distances of means and of standard deviations, position by position."""
    a = moments(selected, *by)
    b = moments(test).select("pos", F.col("mu").alias("mu_t"), F.col("sd").alias("sd_t"))
    both = a.join(F.broadcast(b), "pos")  # d rows
    mean, spread = F.sum((F.col("mu") - F.col("mu_t")) ** 2), F.sum((F.col("sd") - F.col("sd_t")) ** 2)
    return both.groupBy(*by).agg(mean.alias("mean_part"), spread.alias("spread_part"), (mean + spread).alias("moment"))


def _gram(vectors: DataFrame, d: int) -> tuple[int, np.ndarray, np.ndarray]:
    """Count, sum and Gram matrix from one partial row for each task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, s, g = 0, np.zeros(d), np.zeros((d, d))
        for batch in batches:
            x, _ = V.matrix(batch.column(0), d)
            n, s, g = n + len(x), s + x.sum(axis=0), g + x.T @ x
        yield pa.RecordBatch.from_arrays([pa.array([np.concatenate(([n], s, g.ravel())).tolist()], pa.list_(pa.float64()))], ["part"])

    parts = vectors.select("vec").mapInArrow(run, "part array<double>").select(F.posexplode("part").alias("i", "x")).groupBy("i").agg(F.sum("x").alias("x"))
    flat = np.zeros(1 + d + d * d)
    for r in parts.collect():  # 1 + d + d * d numbers
        flat[r["i"]] = r["x"]
    return int(flat[0]), flat[1 : d + 1], flat[d + 1 :].reshape(d, d)


def moment_distance_full(selected: DataFrame, test: DataFrame, d: int) -> float:
    """With full covariances: squared mean distance + tr(A + B - 2 (A^1/2 B A^1/2)^1/2)."""
    stats = []
    for part in (selected, test):
        n, s, g = _gram(part, d)
        mu = s / max(n, 1)
        stats.append((mu, g / max(n, 1) - np.outer(mu, mu)))
    (m1, a), (m2, b) = stats
    w, q = np.linalg.eigh(a)
    root = (q * np.sqrt(np.maximum(w, 0))) @ q.T
    cross = np.sqrt(np.maximum(np.linalg.eigvalsh(root @ b @ root), 0)).sum()
    return float(((m1 - m2) ** 2).sum() + np.trace(a) + np.trace(b) - 2 * cross)


def pooled(vec: Column, side: int, cell: int) -> Column:
    """Mean pooling of a side x side image into (side / cell)^2 values, in one array."""
    out = side // cell
    cells = [[(r * cell + i) * side + c * cell + j for i in range(cell) for j in range(cell)] for r in range(out) for c in range(out)]
    return F.array(*[sum((F.get(vec, F.lit(p)) for p in ps[1:]), F.get(vec, F.lit(ps[0]))) / float(cell * cell) for ps in cells])


def expanded(low: Column, side: int, cell: int) -> Column:
    """Repeat pooled values back to side x side."""
    out = side // cell
    return F.array(*[F.get(low, F.lit((p // side // cell) * out + p % side // cell)) for p in range(side * side)])


def square_gap(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def paired_feature_distance(pairs: DataFrame, a: str = "a", b: str = "b", side: int = 8, *by: str) -> DataFrame:
    """by, paired: mean over pairs of the squared distances of unit vectors after pooling by 1, 2 and 4, averaged."""
    terms = [square_gap(V.l2_normalize(pooled(F.col(a), side, c) if c > 1 else F.col(a)), V.l2_normalize(pooled(F.col(b), side, c) if c > 1 else F.col(b))) for c in (1, 2, 4)]
    value = sum(terms[1:], terms[0]) / 3.0
    return pairs.groupBy(*by).agg(F.avg(value).alias("paired"))


def super_resolution(selected: DataFrame, test: DataFrame, side: int = 8, cell: int = 4) -> DataFrame:
    """(test_id, truth, guess): each held-out row's low version finds the nearest low version in the subset; its high version is the guess."""
    low = lambda df: df.select("sample_id", pooled(F.col("vec"), side, cell).alias("vec"))
    found = nearest_rows(low(selected), low(test), 1).select("ref_id", "sample_id")
    return found.join(selected.select("sample_id", F.col("vec").alias("guess")), "sample_id").join(test.select(F.col("sample_id").alias("ref_id"), F.col("vec").alias("truth")), "ref_id").select(F.col("ref_id").alias("test_id"), "truth", "guess")


def condition_means(selected: DataFrame, condition: str) -> DataFrame:
    parts = selected.select(condition, F.posexplode("vec").alias("pos", "x")).groupBy(condition, "pos").agg(F.avg("x").alias("x"))
    return parts.groupBy(condition).agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "x"))), lambda s: s["x"]).alias("guess"))  # d entries a condition


def from_condition(selected: DataFrame, test: DataFrame, condition: str) -> DataFrame:
    """(test_id, truth, guess): the subset's mean for the held-out row's condition; guess is null without support."""
    return test.join(condition_means(selected, condition), condition, "left").select(F.col("sample_id").alias("test_id"), F.col("vec").alias("truth"), "guess")


def balance(selected: DataFrame, key: str, k: int | None = None) -> DataFrame:
    """(groups, rows, evenness, min_share, max_share, gini) of the rows over the groups; k counts empty groups too."""
    counts = selected.groupBy(key).agg(F.count(F.lit(1)).alias("n"))
    place = F.row_number().over(Window.orderBy("n", key))  # K rows
    rows = counts.withColumn("i", place)
    groups, total = F.count(F.lit(1)), F.sum("n").cast("double")
    cells = F.lit(k) if k else groups
    h = F.ln(total) - F.sum(F.col("n") * F.ln(F.col("n").cast("double"))) / total
    empty = cells - groups
    gini = (2 * F.sum((F.col("i") + 0) * F.col("n")) + 2 * empty * total) / (cells * total) - (cells + 1) / cells.cast("double")
    least = F.when(empty > 0, 0.0).otherwise(F.min("n") / total)
    return rows.agg(groups.alias("groups"), F.sum("n").alias("rows"), F.when(cells > 1, h / F.ln(cells.cast("double"))).otherwise(1.0).alias("evenness"), least.alias("min_share"), (F.max("n") / total).alias("max_share"), gini.alias("gini"))


def representativeness(selected: DataFrame, pool: DataFrame, picks: DataFrame) -> DataFrame:
    """(to_centroid, pool_to_subset): mean similarity of picks to their centroid, and of pool rows to their nearest pick."""
    a = selected.agg(F.avg("sim").alias("to_centroid"))
    return a.crossJoin(best_similarity(pool, picks).agg(F.avg("best").alias("pool_to_subset")))


def redundancy(vectors: DataFrame, least: float) -> DataFrame:
    """(n, with_neighbour, share): rows that have another row at similarity least or more."""
    near = similar_rows(vectors, least).withColumn("near", F.lit(1))
    both = vectors.select("sample_id").join(near, "sample_id", "left")
    return both.agg(F.count(F.lit(1)).alias("n"), F.count("near").alias("with_neighbour"), (F.count("near") / F.count(F.lit(1))).alias("share"))


def entropy_profile(scored: DataFrame, kept: DataFrame) -> DataFrame:
    """(part, n, mean_h, min_h, median_h, max_h) of kept and dropped rows."""
    flag = scored.join(kept.select("sample_id").withColumn("part", F.lit("kept")), "sample_id", "left").withColumn("part", F.coalesce("part", F.lit("dropped")))
    middle = group_median(flag.withColumn("_h", F.round("entropy", 9)), "part", "_h", "sample_id").select("part", F.col("median").alias("median_h"))
    facts = flag.groupBy("part").agg(F.count(F.lit(1)).alias("n"), F.avg("entropy").alias("mean_h"), F.min("entropy").alias("min_h"), F.max("entropy").alias("max_h"))
    return facts.join(F.broadcast(middle), "part").select("part", "n", "mean_h", "min_h", "median_h", "max_h")  # two rows


def purity(assigned: DataFrame, labels: DataFrame) -> DataFrame:
    """(n, purity, mean_sim): share of rows whose label is the commonest of their cluster."""
    both = assigned.filter("cluster_id IS NOT NULL").join(labels, "sample_id")
    top = both.groupBy("cluster_id", "label").agg(F.count(F.lit(1)).alias("n"), F.sum("sim").alias("s")).groupBy("cluster_id").agg(F.max("n").alias("top"), F.sum("n").alias("n"), F.sum("s").alias("s"))
    return top.agg(F.sum("n").alias("n"), (F.sum("top") / F.sum("n")).alias("purity"), (F.sum("s") / F.sum("n")).alias("mean_sim"))


def overlap(a: DataFrame, b: DataFrame) -> DataFrame:
    """(n_a, n_b, both, jaccard)"""
    x = a.select("sample_id").distinct().withColumn("x", F.lit(1)).join(b.select("sample_id").distinct().withColumn("y", F.lit(1)), "sample_id", "full")
    both = F.count(F.when(F.col("x").isNotNull() & F.col("y").isNotNull(), 1))
    return x.agg(F.count("x").alias("n_a"), F.count("y").alias("n_b"), both.alias("both"), (both / F.count(F.lit(1))).alias("jaccard"))


def convergence(selected: DataFrame, test: DataFrame, batch: int = 256, seed: int = 42, by: str = "method", planner: SelectionPlanner = DEFAULT) -> DataFrame:
    """by, step, n, moment: mini-batches in hash order update running moments; the distance to the held-out rows after each step."""
    keys = stage(selected.sparkSession, selected.select(by, "sample_id", (-hash_order(seed=seed)).alias("_h")), "keys")
    place = rank_in_group(keys, by, "_h", "sample_id", "_r", planner).select(by, "sample_id", (F.floor((F.col("_r") - 1) / batch) + 1).cast("long").alias("step"))
    long = selected.join(place, [by, "sample_id"]).select(by, "step", F.posexplode("vec").alias("pos", "x"))
    sums = long.groupBy(by, "step", "pos").agg(F.sum("x").alias("s"), F.sum(F.col("x") * F.col("x")).alias("ss"), F.count(F.lit(1)).alias("c"))
    run = Window.partitionBy(by, "pos").orderBy("step")
    acc = sums.select(by, "step", "pos", F.sum("s").over(run).alias("s"), F.sum("ss").over(run).alias("ss"), F.sum("c").over(run).alias("n"))
    mu = F.col("s") / F.col("n")
    acc = acc.select(by, "step", "pos", "n", mu.alias("mu"), F.sqrt(F.greatest(F.lit(0.0), F.col("ss") / F.col("n") - mu * mu)).alias("sd"))
    goal = moments(test).select("pos", F.col("mu").alias("mu_t"), F.col("sd").alias("sd_t"))
    gap = (F.col("mu") - F.col("mu_t")) ** 2 + (F.col("sd") - F.col("sd_t")) ** 2
    return acc.join(F.broadcast(goal), "pos").groupBy(by, "step").agg(F.max("n").alias("n"), F.sum(gap).alias("moment"))


def steps_to_target(curves: DataFrame, target: float, by: str = "method") -> DataFrame:
    """by, steps: the first step at or below the target; null if never."""
    return curves.groupBy(by).agg(F.min(F.when(F.col("moment") <= target, F.col("step"))).alias("steps"))


def selection_stats(n_total: int, selected: DataFrame) -> DataFrame:
    return selected.agg(F.count(F.lit(1)).alias("n")).select(F.lit(n_total).cast("long").alias("n_total"), "n", (1 - F.col("n") / F.lit(n_total)).alias("pruned"))


def improvement(results: DataFrame, value: str, best: str, key: str = "method") -> DataFrame:
    """(best, next_best, improvement): share by which the method named best lowers the lowest other value."""
    a, b = F.min(F.when(F.col(key) == best, F.col(value))), F.min(F.when(F.col(key) != best, F.col(value)))
    return results.agg(a.alias("best"), b.alias("next_best"), ((b - a) / b).alias("improvement"))


def op_counts(n: int, k: int, d: int, payload: int, iters: int, ref: int) -> dict[str, float]:
    """Operations by step: entropy N, centroids T*R*K*d, assignment N*K*d, sampling N*log2(N/K)."""
    return {"entropy": float(n * payload), "centroids": float(iters * ref * k * d), "assignment": float(n * k * d), "sampling": n * math.log2(max(n / k, 2))}


def _stages(spark: SparkSession) -> dict[int, int]:
    """Shuffle bytes written by each stage that the session's status store still holds."""
    sc = spark.sparkContext
    sc._jsc.sc().listenerBus().waitUntilEmpty()
    found = sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(sc._gateway.jvm.double, 0), None)
    return {s.stageId(): s.shuffleWriteBytes() for s in (found.apply(i) for i in range(found.size()))}


class CostReport:
    """with CostReport(spark) as c: ...; c.seconds has the wall time of the block, c.shuffle_bytes what its stages wrote for exchanges.

    Stages of other threads count too; without a session only the time is taken.
    """

    def __init__(self, spark: SparkSession | None = None):
        self._spark, self.shuffle_bytes = spark, None

    def __enter__(self) -> CostReport:
        self._last = max(_stages(self._spark), default=-1) if self._spark else -1
        self._t = time.perf_counter()
        return self

    def __exit__(self, *_) -> None:
        self.seconds = time.perf_counter() - self._t
        if self._spark:
            self.shuffle_bytes = sum(b for i, b in _stages(self._spark).items() if i > self._last)
