"""Stage II, prior centroids: reference banks, spherical k-means and its alternatives."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import vectors as V
from ..sources.tables import stage


LOCAL_NUMBERS = 8_000_000  # 64 MB of doubles


@dataclass
class CentroidModel:
    """K unit vectors. K times d numbers: fixed by parameters, so broadcasting them is bounded."""

    matrix: np.ndarray
    history: list[float] = field(default_factory=list)

    @property
    def k(self) -> int:
        return len(self.matrix)

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(i, row.tolist()) for i, row in enumerate(self.matrix)], "cluster_id int, centroid array<double>")

    def save(self, spark: SparkSession, path: str) -> None:
        self.frame(spark).coalesce(1).write.mode("overwrite").parquet(path)

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> CentroidModel:
        rows = spark.read.parquet(path).orderBy("cluster_id").collect()
        return cls(np.array([r["centroid"] for r in rows]))


def reference_bank(banks: dict[str, DataFrame], names: list[str] | None = None) -> DataFrame:
    """(bank, sample_id, vec, class_label): union of the chosen banks, classes and all."""
    out = None
    for name in names if names is not None else banks:
        part = banks[name].select(F.lit(name).alias("bank"), "sample_id", "vec", F.col("class_label").cast("string").alias("class_label"))
        out = part if out is None else out.unionByName(part)
    if out is None:
        raise ValueError("no bank chosen")
    return out


def seed_rows(ref: DataFrame, k: int, init: str = "first_k", seed: int = 42) -> np.ndarray:
    """K unit rows of ref: first_k by id, hash_order, or farthest_first (max-min, starting at the first id)."""
    unit = ref.select("sample_id", V.l2_normalize(F.col("vec")).alias("z")).filter("z IS NOT NULL")
    if init == "first_k":
        rows = unit.orderBy("sample_id").limit(k).collect()
    elif init == "hash_order":
        rows = unit.orderBy(F.md5(F.concat(F.lit(f"{seed}:"), F.col("sample_id").cast("string"))), "sample_id").limit(k).collect()
    elif init == "farthest_first":
        unit = stage(ref.sparkSession, unit, "unit")
        rows = unit.orderBy("sample_id").limit(1).collect()
        while 0 < len(rows) < k:
            nxt = _farthest(unit, rows)
            if not nxt:
                break
            rows += nxt
    else:
        raise ValueError(f"unknown init {init}")
    if len(rows) < k:
        raise ValueError(f"{k} clusters need as many usable reference rows, not {len(rows)}")
    return np.array([r["z"] for r in rows])


def _farthest(unit: DataFrame, rows: list) -> list:
    """The row whose largest similarity, rounded to 9 digits, with the chosen rows is least; one candidate for each task."""
    shared = unit.sparkSession.sparkContext.broadcast((np.array([r["z"] for r in rows]), np.array([r["sample_id"] for r in rows])))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c, taken = shared.value
        best = None
        for batch in batches:
            ids, (z, _) = np.asarray(batch.column(0)), V.matrix(batch.column(1), c.shape[1])
            free = np.flatnonzero(~np.isin(ids, taken))
            if len(free):
                near = np.round((z[free] @ c.T).max(axis=1), 9)
                at = np.lexsort((ids[free], near))[0]
                best = min(filter(None, (best, (float(near[at]), int(ids[free][at]), z[free][at].tolist()))))
        if best is not None:
            yield pa.RecordBatch.from_arrays([pa.array([best[0]]), pa.array([best[1]]), pa.array([best[2]], pa.list_(pa.float64()))], ["near", "sample_id", "z"])

    found = unit.mapInArrow(run, "near double, sample_id long, z array<double>").orderBy("near", "sample_id").limit(1).collect()
    shared.destroy()
    return found


def _partial_sums(ref: DataFrame, centres: np.ndarray) -> DataFrame:
    """(cluster, pos, s, n): sums of each cluster's unit vectors, one partial row for each cluster and task before the exchange."""
    shared = ref.sparkSession.sparkContext.broadcast(centres)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = shared.value
        sums, n, gain = np.zeros_like(c), np.zeros(len(c), np.int64), np.zeros(len(c))
        for batch in batches:
            z, ok = V.unit_rows(V.matrix(batch.column(0), c.shape[1])[0])
            more = cluster_sums(z[ok], c)
            sums, n, gain = sums + more[0], n + more[1], gain + more[2]
        some = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(sums[some].tolist(), pa.list_(pa.float64())), pa.array(n[some]), pa.array(gain[some])], ["cluster", "sums", "n", "gain"])

    parts = ref.select("vec").mapInArrow(run, "cluster long, sums array<double>, n long, gain double")
    return parts.select("cluster", "n", "gain", F.posexplode("sums").alias("pos", "s")).groupBy("cluster", "pos").agg(F.sum("s").alias("s"), F.sum("n").alias("n"), F.sum("gain").alias("gain"))


def cluster_sums(z: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sum of unit rows, number and summed similarity of every centre's rows."""
    sim = z @ c.T
    at = best_of(sim)
    order = np.argsort(at, kind="stable")
    begin = np.flatnonzero(np.diff(at[order], prepend=-1))
    sums = np.zeros_like(c)
    if len(begin):
        sums[at[order][begin]] = np.add.reduceat(z[order], begin)
    return sums, np.bincount(at, minlength=len(c)), np.bincount(at, weights=sim[np.arange(len(at)), at], minlength=len(c))


def best_of(sim: np.ndarray) -> np.ndarray:
    """Index of the largest similarity rounded to 9 digits; the smaller index on ties."""
    at = sim.argmax(axis=1)
    close = sim >= (sim[np.arange(len(sim)), at] - 1e-9)[:, None]
    rows = np.flatnonzero(close.sum(axis=1) > 1)  # only near ties are rounded
    at[rows] = np.round(sim[rows], 9).argmax(axis=1)
    return at


def fit_centroids(ref: DataFrame, k: int, iters: int = 5, init: str = "first_k", seed: int = 42, tol: float = 0.0, local_numbers: int = LOCAL_NUMBERS) -> CentroidModel:
    """Spherical k-means over all classes of the bank at once: assign by cosine, sum, renormalise; an empty cluster keeps its centre.

    A bank of at most local_numbers numbers (rows times dimensions, counted first) is clustered in the driver's memory,
    where a round costs no job; a larger one, or a whole pool, in one distributed job a round. Both give the same centres.
    """
    ref = stage(ref.sparkSession, ref.select("sample_id", "vec"), "bank")
    model = CentroidModel(seed_rows(ref, k, init, seed))
    held = None
    if ref.count() * model.matrix.shape[1] <= local_numbers:
        z, ok = V.unit_rows(V.matrix(ref.select("vec").toArrow()["vec"], model.matrix.shape[1])[0])
        held = z[ok]
    for _ in range(iters):
        sums, n, gain = _collected_sums(ref, model.matrix) if held is None else cluster_sums(held, model.matrix)
        unit, ok = V.unit_rows(sums)
        new = np.where(ok[:, None], unit, model.matrix)
        shift = float(np.abs(new - model.matrix).max())
        model.matrix = new
        model.history.append(float(gain.sum()) / max(int(n.sum()), 1))
        if shift <= tol:
            break
    return model


def _collected_sums(ref: DataFrame, centres: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    sums, n, gain = np.zeros_like(centres), np.zeros(len(centres), np.int64), np.zeros(len(centres))
    for r in _partial_sums(ref, centres).collect():  # K * d rows
        sums[r["cluster"], r["pos"]], n[r["cluster"]], gain[r["cluster"]] = r["s"], r["n"], r["gain"]
    return sums, n, gain


def class_centroids(ref: DataFrame, label: str = "class_label") -> DataFrame:
    """(label, centroid): unit mean of every class, the alternative to over-clustering."""
    parts = ref.select(label, F.posexplode(V.l2_normalize(F.col("vec"))).alias("pos", "x")).groupBy(label, "pos").agg(F.sum("x").alias("x"))
    means = parts.groupBy(label).agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "x"))), lambda s: s["x"]).alias("m"))  # d entries a class
    return means.select(label, V.l2_normalize(F.col("m")).alias("centroid")).filter("centroid IS NOT NULL")


def fit_library(ref: DataFrame, k: int, iters: int = 20, seed: int = 42) -> CentroidModel:
    """The library's k-means under cosine distance; it may return fewer centres than k."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    data = ref.select(array_to_vector("vec").alias("features"))
    fitted = KMeans(k=k, maxIter=iters, seed=seed, distanceMeasure="cosine", initMode="k-means||").fit(data)
    return CentroidModel(V.unit_rows(np.array(fitted.clusterCenters()))[0])


def fit_minibatch(pool: DataFrame, k: int, batches: int = 20, batch_share: int = 10, init: str = "first_k", seed: int = 42) -> CentroidModel:
    """Mini-batch spherical k-means: each step takes one hash slice in batch_share; a centre moves by 1 / (rows it has seen)."""
    pool = stage(pool.sparkSession, pool.select("sample_id", "vec"), "pool")
    model, seen = CentroidModel(seed_rows(pool, k, init, seed)), np.zeros(k)
    for step in range(batches):
        key = F.md5(F.concat(F.lit(f"{seed}:{step // batch_share}:"), F.col("sample_id").cast("string")))
        part = pool.filter(F.conv(F.substring(key, 1, 8), 16, 10).cast("long") % batch_share == step % batch_share)
        sums, n, _ = _collected_sums(part, model.matrix)
        seen += n
        some = n > 0
        rate = np.where(some, n / np.maximum(seen, 1), 0)[:, None]
        moved, ok = V.unit_rows((1 - rate) * model.matrix + rate * sums / np.maximum(n, 1)[:, None])
        model.matrix = np.where((some & ok)[:, None], moved, model.matrix)
    return model
