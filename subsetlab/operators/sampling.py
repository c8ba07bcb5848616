"""Stage II, budgeted sampling: equal quotas, nearest first, global refill; allocation and order variants."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.tables import stage
from .select import DEFAULT, SelectionPlanner, flag_top_q, group_median, rank_in_group, top_n, top_q_per_group

ORDERS = ("nearest", "farthest", "median", "random")


def equal_quota(budget: int, k: int) -> int:
    return max(0, budget) // k


def hash_order(column: str = "sample_id", seed: int = 42):
    """Engine-independent pseudo-random order: the first 52 bits of an MD5 as an integer."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.col(column).cast("string"))), 1, 13), 16, 10).cast("long")


def with_priority(assigned: DataFrame, order: str = "nearest", seed: int = 42, planner: SelectionPlanner = DEFAULT) -> DataFrame:
    """assigned rows that have a cluster, plus _score: larger is taken first."""
    rows = assigned.filter("cluster_id IS NOT NULL")
    sim = F.round("sim", 9)
    if order == "nearest":
        return rows.withColumn("_score", sim)
    if order == "farthest":
        return rows.withColumn("_score", -sim)
    if order == "random":
        return rows.withColumn("_score", -hash_order(seed=seed).cast("double"))
    if order == "median":
        middle = group_median(rows.withColumn("_sim", sim), "cluster_id", "_sim", "sample_id", planner).select("cluster_id", F.col("median").alias("_mid"))
        return rows.join(F.broadcast(middle), "cluster_id").withColumn("_score", -F.round(F.abs(sim - F.col("_mid")), 9)).drop("_mid")  # K rows
    raise ValueError(f"order is one of {ORDERS}")


def take_quota(assigned: DataFrame, q: int, order: str = "nearest", planner: SelectionPlanner = DEFAULT, seed: int = 42) -> DataFrame:
    """The q first rows of every pool; pools with fewer rows are kept whole."""
    return top_q_per_group(with_priority(assigned, order, seed, planner), "cluster_id", q, "_score", "sample_id", planner).drop("_score")


def scene_sample(assigned: DataFrame, budget: int, k: int, order: str = "nearest", planner: SelectionPlanner = DEFAULT, ranks: bool = True) -> DataFrame:
    """(sample_id, cluster_id, sim, rank_in_cluster, picked_by): exactly min(budget, usable rows) rows.

    Quota picks first; what rare pools and the floor remainder leave open is filled from all unpicked rows by similarity.
    rank_in_cluster counts within the selection, which for the nearest order is the rank in the pool; ranks=False leaves it out.
    """
    spark = assigned.sparkSession
    flagged = flag_top_q(with_priority(assigned, order, planner=planner), "cluster_id", equal_quota(budget, k), "_score", "sample_id", planner)
    flagged = stage(spark, flagged.select("sample_id", "cluster_id", "sim", "_score", "picked"), "flagged")
    quota = flagged.filter("picked")
    short = max(0, budget) - quota.count()
    fill = top_n(flagged.filter("NOT picked").withColumn("_sim", F.round("sim", 9)), short, "_sim", "sample_id", planner).drop("_sim")
    both = quota.withColumn("picked_by", F.lit("quota")).unionByName(fill.withColumn("picked_by", F.lit("refill"))).drop("picked")
    if not ranks:
        return both.select("sample_id", "cluster_id", "sim", "picked_by")
    ranked = rank_in_group(stage(spark, both, "picks"), "cluster_id", "_score", "sample_id", "rank_in_cluster", planner)
    return ranked.select("sample_id", "cluster_id", "sim", "rank_in_cluster", "picked_by")


def refill(assigned: DataFrame, budget: int, k: int) -> DataFrame:
    return scene_sample(assigned, budget, k).filter("picked_by = 'refill'")


def scene_sample_single_plan(assigned: DataFrame, budget: int, k: int) -> DataFrame:
    """The same selection in one lazy plan of two windows, the second over one task: for small pools and for checking the other form."""
    rows = assigned.filter("cluster_id IS NOT NULL").withColumn("rank_in_cluster", F.row_number().over(Window.partitionBy("cluster_id").orderBy(F.round("sim", 9).desc(), "sample_id")))
    late = F.when(F.col("rank_in_cluster") <= equal_quota(budget, k), 0).otherwise(1)
    place = F.row_number().over(Window.orderBy(late, F.round("sim", 9).desc(), "sample_id"))
    kept = rows.withColumn("_late", late).withColumn("_place", place).filter(F.col("_place") <= budget)
    return kept.select("sample_id", "cluster_id", "sim", "rank_in_cluster", F.when(F.col("_late") == 0, "quota").otherwise("refill").alias("picked_by"))


def allocate(pools: DataFrame, budget: int, policy: str) -> DataFrame:
    """(cluster_id, n, quota) from (cluster_id, n): equal, proportional, sqrt or waterfill; K rows.

    Shares are floored and cut at the pool; waterfill raises a common level until the budget is met, the rest of it going
    one by one to the smallest cluster ids that still have rows.
    """
    if policy == "waterfill":
        by_size, upto = Window.orderBy("n", "cluster_id"), Window.orderBy("n", "cluster_id").rowsBetween(Window.unboundedPreceding, -1)
        rows = pools.withColumn("_before", F.coalesce(F.sum("n").over(upto), F.lit(0))).withColumn("_left", F.count(F.lit(1)).over(Window.partitionBy()) - F.row_number().over(by_size) + 1)
        # the level stays at the first pool that is not used up
        rows = rows.withColumn("_level", F.floor((F.lit(budget) - F.col("_before")) / F.col("_left"))).withColumn("_open", F.col("_level") < F.col("n"))
        level = rows.filter("_open").orderBy("n", "cluster_id").limit(1).select(F.col("_level").alias("_l"), (F.lit(budget) - F.col("_before") - F.col("_level") * F.col("_left")).alias("_extra"))
        rows = rows.select("cluster_id", "n").join(F.broadcast(level), F.lit(True), "left")
        more = F.row_number().over(Window.partitionBy(F.col("n") > F.col("_l")).orderBy("cluster_id"))
        quota = F.when(F.col("_l").isNull(), F.col("n")).when(F.col("n") > F.col("_l"), F.col("_l") + (more <= F.col("_extra")).cast("long")).otherwise(F.col("n"))
        return rows.select("cluster_id", "n", quota.cast("long").alias("quota"))
    weight = {"equal": F.lit(1.0), "proportional": F.col("n").cast("double"), "sqrt": F.sqrt(F.col("n").cast("double"))}[policy]
    share = F.floor(F.round(F.lit(float(budget)) * weight / F.sum(weight).over(Window.partitionBy()), 9))
    return pools.select("cluster_id", "n", F.least(F.col("n"), share).cast("long").alias("quota"))


def take_allocated(assigned: DataFrame, quotas: DataFrame, planner: SelectionPlanner = DEFAULT) -> DataFrame:
    """The first quota rows of every pool under (cluster_id, quota), nearest first; quotas has K rows."""
    quotas = stage(assigned.sparkSession, quotas.select("cluster_id", "quota"), "quotas")
    return flag_top_q(with_priority(assigned), "cluster_id", quotas, "_score", "sample_id", planner).filter("picked").drop("picked", "_score")
