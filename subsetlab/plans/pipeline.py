"""The two-stage method end to end."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.assign import assign_clusters, pool_sizes
from ..operators.centroids import CentroidModel
from ..operators.entropy import prune_top_fraction
from ..operators.sampling import scene_sample
from ..operators.select import DEFAULT, SelectionPlanner
from ..sources.tables import stage


BROADCAST_IDS = 2_000_000  # survivors whose ids are broadcast at most


def budget_of(n: int, rho_bp: int) -> int:
    """floor((1 - rho) * N), rho in basis points of the original set."""
    return n * (10_000 - rho_bp) // 10_000


def default_stage1_keep(rho_bp: int) -> int:
    """30 % where at most 15 % stay; else twice the kept share, at most all."""
    keep = 10_000 - rho_bp
    return 3000 if keep <= 1500 else min(10_000, 2 * keep)


@dataclass
class PruneResult:
    selected: DataFrame  # sample_id, cluster_id, sim, rank_in_cluster, picked_by
    pools: DataFrame | None  # cluster_id, n
    n_total: int
    n_stage1: int
    budget: int


def prune(scored: DataFrame, vectors: DataFrame, model: CentroidModel | None, rho_bp: int, stage1_keep_bp: int | None = None, stage2: bool = True, planner: SelectionPlanner = DEFAULT) -> PruneResult:
    """scored has (sample_id, entropy); vectors (sample_id, vec), which only survivors of stage I are read for.

    stage2=False keeps the (1 - rho) rows of highest entropy; stage1_keep_bp=10000 skips stage I.
    """
    spark = scored.sparkSession
    scored = stage(spark, scored.select("sample_id", "entropy"), "scores")
    n = scored.count()
    budget = budget_of(n, rho_bp)
    if not stage2:
        kept = prune_top_fraction(scored, 10_000 - rho_bp, n, planner=planner)
        none = F.lit(None)
        out = kept.select("sample_id", none.cast("int").alias("cluster_id"), none.cast("double").alias("sim"), none.cast("int").alias("rank_in_cluster"), F.lit("entropy").alias("picked_by"))
        return PruneResult(out, None, n, budget, budget)
    keep = default_stage1_keep(rho_bp) if stage1_keep_bp is None else stage1_keep_bp
    survivors = scored if keep >= 10_000 else prune_top_fraction(scored, keep, n, planner=planner)
    survivors = survivors.select("sample_id")
    if keep >= 10_000 or n * keep // 10_000 > BROADCAST_IDS:  # wide vectors are not exchanged: all are assigned in a map-only pass, narrow rows meet
        assigned = assign_clusters(vectors, model).join(survivors, "sample_id", "left_semi")
    else:
        assigned = assign_clusters(vectors.join(F.broadcast(survivors), "sample_id", "left_semi"), model)
    assigned = stage(spark, assigned, "assigned")
    return PruneResult(scene_sample(assigned, budget, model.k, planner=planner), pool_sizes(assigned, model.k), n, n * keep // 10_000, budget)
