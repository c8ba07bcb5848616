"""Baselines that the two-stage method is compared with. All return sample_id (and what they ranked by).

The paper names them and little more; where a definition is ours the docstring says so.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import vectors as V
from ..sources.tables import stage
from .assign import assign_clusters
from .centroids import CentroidModel, class_centroids, fit_centroids, fit_minibatch
from .features import random_projection
from .pairs import drop_near_copies, retrieved, similar_pairs
from .sampling import allocate, hash_order, scene_sample, take_allocated, take_quota
from .select import DEFAULT, SelectionPlanner, flag_top_q, group_median, top_n, top_q_per_group

def full(samples: DataFrame) -> DataFrame:
    return samples.select("sample_id")


def random_rows(samples: DataFrame, budget: int, seed: int = 42) -> DataFrame:
    """Uniform: the first rows in hash order."""
    keyed = samples.select("sample_id", (-hash_order(seed=seed)).alias("_k"))
    return top_n(keyed, budget, "_k", "sample_id").select("sample_id")


def moderate_distance(vectors: DataFrame, group: str, budget: int, planner: SelectionPlanner = DEFAULT, gaps: tuple[DataFrame, DataFrame] | None = None) -> DataFrame:
    """(sample_id, gap): rows whose distance from their group's centre is nearest to the group's median distance.

    Groups get a share of the budget in proportion (floored); what is left goes to the smallest gaps anywhere. Ours in
    detail: distance is one minus cosine. gaps may hold what moderate_gaps gives for these vectors.
    """
    gaps, middle = gaps or moderate_gaps(vectors, group, planner)
    total = gaps.count()
    quotas = middle.select(group, F.floor(F.lit(budget) * F.col("n") / F.lit(max(total, 1))).alias("quota"))
    scored = flag_top_q(gaps, group, quotas, "_near", "sample_id", planner).withColumn("_k", F.when(F.col("picked"), 10.0).otherwise(0.0) + F.col("_near"))
    return top_n(scored, budget, "_k", "sample_id", planner).select("sample_id", (-F.col("_near")).alias("gap"))


def moderate_gaps(vectors: DataFrame, group: str, planner: SelectionPlanner = DEFAULT) -> tuple[DataFrame, DataFrame]:
    """Tables (sample_id, group, _near), the negative gaps, and (group, median, n): the part of moderate_distance without a budget."""
    centres = class_centroids(vectors.select("sample_id", "vec", group), group)
    z = V.l2_normalize(F.col("vec"))
    far = vectors.join(F.broadcast(centres), group).select("sample_id", group, F.round(1 - V.dot(z, F.col("centroid")), 9).alias("dist"))
    far = stage(vectors.sparkSession, far.filter("dist IS NOT NULL"), "distances")
    middle = stage(vectors.sparkSession, group_median(far, group, "dist", "sample_id", planner), "medians")
    near = -F.round(F.abs(F.col("dist") - F.col("median")), 9)
    return stage(vectors.sparkSession, far.join(planner.small(middle), group).select("sample_id", group, near.alias("_near")), "gaps"), middle


def cluster_nearest(pool: DataFrame, k: int, budget: int, iters: int = 5) -> DataFrame:
    """Direct clustering of the whole pool, equal quotas, nearest first; no reference and no entropy."""
    model = fit_centroids(pool, k, iters)
    return scene_sample(assign_clusters(pool, model), budget, k)


def retrieval_nearest(pool: DataFrame, ref: DataFrame, budget: int, m: int = 4, copies: float | None = None) -> DataFrame:
    """(sample_id, best): rows that some curated row retrieves among its m nearest come first, then the best similarity.

    copies: similarity from which on pool rows count as copies of one another; of those only the first stays for retrieval.
    """
    if copies is not None:
        pool = drop_near_copies(pool, copies)
    return best_retrieved(retrieved(pool, ref, m), budget)


def best_retrieved(scored: DataFrame, budget: int) -> DataFrame:
    """(sample_id, best) of a table from pairs.retrieved, for any budget: hits first, then the best similarity."""
    keyed = scored.withColumn("_k", F.round("best", 9) + F.when(F.col("hit"), 10.0).otherwise(0.0))
    return top_n(keyed, budget, "_k", "sample_id").select("sample_id", "best")


def retrieval_clusters(pool: DataFrame, ref: DataFrame, model: CentroidModel, budget: int) -> DataFrame:
    """Rows of the clusters that curated rows hit, shares in proportion to the hits (floored), nearest first."""
    hits = assign_clusters(ref, model).filter("cluster_id IS NOT NULL").groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n"))
    quotas = allocate(hits, budget, "proportional").withColumn("quota", F.floor(F.round(F.lit(float(budget)) * F.col("n") / F.sum("n").over(Window.partitionBy()), 9)))
    return take_allocated(assign_clusters(pool, model), quotas).select("sample_id", "cluster_id", "sim")


def anchor_stratified(samples: DataFrame, strata: list[Column], budget: int, seed: int = 42, planner: SelectionPlanner = DEFAULT) -> DataFrame:
    """Equal hash-random shares of coarse strata, the rest in hash order from all. The paper's baseline is undescribed; this is ours."""
    keyed = samples.select("sample_id", F.concat_ws("|", *strata).alias("stratum"), (-hash_order(seed=seed)).alias("_h"))
    n = keyed.select("stratum").distinct().count()
    flagged = flag_top_q(keyed, "stratum", budget // max(n, 1), "_h", "sample_id", planner)
    # 52-bit hashes stay exact in a double next to the flag
    scored = flagged.withColumn("_k", F.when(F.col("picked"), F.lit(float(1 << 52))).otherwise(F.lit(0.0)) + F.col("_h").cast("double"))
    return top_n(scored, budget, "_k", "sample_id", planner).select("sample_id", "stratum")


def informative_classes(samples: DataFrame, scored: DataFrame, group: str, tau: float) -> DataFrame:
    """(group): classes whose mean entropy is at least tau, for leaving out those of little information as a whole."""
    means = samples.select("sample_id", group).join(scored.select("sample_id", "entropy"), "sample_id").groupBy(group).agg(F.avg("entropy").alias("mean"))
    return means.filter(F.round("mean", 9) >= tau).select(group)


def rule_curation(docs: DataFrame, scored: DataFrame, min_chars: int, tau: float, per_source: int, class_tau: float | None = None, vectors: DataFrame | None = None, copies: float = 0.95, planner: SelectionPlanner = DEFAULT) -> DataFrame:
    """(sample_id, source): one row of each equal text, size and entropy floors, a cap for each source in hash order. Rules are ours.

    class_tau leaves out sources of a lower mean entropy; with vectors (sample_id, vec) also the near copies, from the
    similarity copies on, of smaller ids. Equal texts are told by a 256-bit digest, so only digests and ids are exchanged.
    """
    long = docs.filter(F.length("payload") >= min_chars).select("sample_id", "source", F.sha2("payload", 256).alias("digest"))
    first = long.groupBy("digest").agg(F.min(F.struct("sample_id", "source")).alias("r")).select("r.*")
    kept = first.join(scored.filter(F.col("entropy") >= tau).select("sample_id"), "sample_id", "left_semi")
    if class_tau is not None:
        classes = stage(docs.sparkSession, informative_classes(docs, scored, "source", class_tau), "classes")
        kept = kept.join(planner.small(classes), "source", "left_semi").select("sample_id", "source")
    if vectors is not None:
        kept = stage(docs.sparkSession, kept, "kept")
        own = vectors.select("sample_id", "vec").join(kept, "sample_id", "left_semi")
        found = stage(docs.sparkSession, similar_pairs(own, copies).select(F.col("b").alias("sample_id")).distinct(), "copies")
        kept = kept.join(found, "sample_id", "left_anti")
    kept = stage(docs.sparkSession, kept.withColumn("_h", -hash_order()), "kept")
    return top_q_per_group(kept, "source", per_source, "_h", "sample_id", planner).select("sample_id", "source")


def score_ranked(samples: DataFrame, scores: DataFrame, budget: int, planner: SelectionPlanner = DEFAULT) -> DataFrame:
    """Supervised: largest score first, hash order within equal scores, whatever the scores' scale. Null and NaN scores are never taken."""
    keyed = samples.select("sample_id").join(scores.select("sample_id", "score"), "sample_id").withColumn("_h", hash_order())
    return top_n(keyed, budget, "score", "sample_id", planner, ties="_h").select("sample_id", "score")


def union_capped(sets: list[DataFrame], cap: int, planner: SelectionPlanner = DEFAULT) -> DataFrame:
    """(bank, sample_id, class_label): concatenated classification sets with at most cap rows of a class in hash order."""
    out = sets[0]
    for s in sets[1:]:
        out = out.unionByName(s)
    keyed = out.withColumn("_class", F.to_json(F.struct("bank", "class_label"))).withColumn("_h", -hash_order())
    return top_q_per_group(keyed, "_class", cap, "_h", "sample_id", planner).drop("_class", "_h")


def centroids_full(pool: DataFrame, k: int, iters: int = 5) -> CentroidModel:
    return fit_centroids(pool, k, iters)


def centroids_minibatch(pool: DataFrame, k: int, d_in: int, d_out: int, batches: int = 20) -> CentroidModel:
    """Mini-batch clustering of an entropy-pruned pool in fewer, renormalised dimensions (random signs: the paper's reduction is not given)."""
    return fit_minibatch(random_projection(pool, d_in, d_out), k, batches)


def centroids_reference(bank: DataFrame, k: int, iters: int = 5) -> CentroidModel:
    return fit_centroids(bank, k, iters)


def nearest_of_pool(assigned: DataFrame, per_cluster: int) -> DataFrame:
    return take_quota(assigned, per_cluster)
