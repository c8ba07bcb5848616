"""Stage II, assignment of samples to their most similar centroid, and candidate pools."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import vectors as V
from .centroids import CentroidModel, best_of


def assign_clusters(vectors: DataFrame, model: CentroidModel, measure: str = "cosine", engine: str = "arrow") -> DataFrame:
    """(sample_id, cluster_id, sim): one map-only pass; vectors leave the plan here. Ties go to the smaller cluster.

    Samples without a unit vector get a null cluster and sim. measure 'inner' ranks by the unnormalised product.
    """
    if measure not in ("cosine", "inner"):
        raise ValueError(f"unknown measure {measure}")
    if engine == "sql":
        long = similarity_matrix(vectors, model, measure)
        best = long.groupBy("sample_id").agg(F.max(F.struct(F.round("sim", 9).alias("r"), (-F.col("cluster_id")).alias("c"), "sim")).alias("b"))
        out = best.select("sample_id", (-F.col("b.c")).alias("cluster_id"), F.col("b.sim").alias("sim"))
        return vectors.select("sample_id").join(out, "sample_id", "left")
    shared = vectors.sparkSession.sparkContext.broadcast(model.matrix)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = shared.value
        for batch in batches:
            x, valid = V.matrix(batch.column(1), c.shape[1])
            z, ok = V.unit_rows(x)
            sim = (z if measure == "cosine" else x) @ c.T
            at = best_of(sim) if len(sim) else np.zeros(0, np.int64)
            cluster, value = np.zeros(batch.num_rows, np.int32), np.zeros(batch.num_rows)
            use = valid[ok]
            cluster[use], value[use] = at[ok], sim[np.arange(len(at)), at][ok]
            none = np.ones(batch.num_rows, bool)
            none[use] = False
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(cluster, mask=none), pa.array(value, mask=none)], ["sample_id", "cluster_id", "sim"])

    return vectors.select("sample_id", "vec").mapInArrow(run, "sample_id long, cluster_id int, sim double")


def similarity_matrix(vectors: DataFrame, model: CentroidModel, measure: str = "cosine") -> DataFrame:
    """(sample_id, cluster_id, sim) for every pair, for inspection: K rows a sample, the K centroids broadcast."""
    z = V.l2_normalize(F.col("vec"))
    ready = vectors.select("sample_id", (z if measure == "cosine" else F.when(z.isNotNull(), F.col("vec"))).alias("z")).filter("z IS NOT NULL")
    return ready.crossJoin(F.broadcast(model.frame(vectors.sparkSession))).select("sample_id", "cluster_id", V.dot(F.col("z"), F.col("centroid")).alias("sim"))


def assign_topk(vectors: DataFrame, model: CentroidModel, m: int) -> DataFrame:
    """(sample_id, rank, cluster_id, sim): the m most similar clusters."""
    shared = vectors.sparkSession.sparkContext.broadcast(model.matrix)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = shared.value
        for batch in batches:
            x, valid = V.matrix(batch.column(1), c.shape[1])
            z, ok = V.unit_rows(x)
            sim = z[ok] @ c.T
            order = np.argsort(-np.round(sim, 9), axis=1, kind="stable")[:, :m]
            ids = np.asarray(batch.column(0))[valid[ok]]
            n = order.shape[1] if len(order) else 0
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(ids, n)), pa.array(np.tile(np.arange(1, n + 1), len(ids))), pa.array(order.ravel().astype(np.int32)), pa.array(np.take_along_axis(sim, order, 1).ravel())], ["sample_id", "rank", "cluster_id", "sim"])

    return vectors.select("sample_id", "vec").mapInArrow(run, "sample_id long, rank long, cluster_id int, sim double")


def margins(vectors: DataFrame, model: CentroidModel) -> DataFrame:
    """(sample_id, margin): best minus second similarity."""
    top = assign_topk(vectors, model, 2)
    return top.groupBy("sample_id").agg((F.max("sim") - F.min("sim")).alias("margin"))


def pool_sizes(assigned: DataFrame, k: int) -> DataFrame:
    """(cluster_id, n) for all k clusters, empty ones too."""
    counts = assigned.filter("cluster_id IS NOT NULL").groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n"))
    every = assigned.sparkSession.range(k).select(F.col("id").cast("int").alias("cluster_id"))
    return every.join(counts, "cluster_id", "left").select("cluster_id", F.coalesce("n", F.lit(0)).alias("n"))
