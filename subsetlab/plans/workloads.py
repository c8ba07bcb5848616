"""The paper's experiments on the given tables: one result row for each setting.

Narrow score and assignment tables are staged once and reused by all settings of a sweep; a sweep tags its selections,
unions them and computes the measures in one grouped pass.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators import baselines as B
from ..operators import measures as M
from ..operators.assign import assign_clusters, pool_sizes
from ..operators.centroids import CentroidModel, fit_centroids
from ..operators.entropy import prune_top_fraction, sample_entropy
from ..operators.pairs import retrieved
from ..operators.sampling import equal_quota, scene_sample
from ..schemas import BYTES
from ..sources.tables import stage
from .pipeline import budget_of, default_stage1_keep


@dataclass
class Bench:
    """Candidates (sample_id, vec, label), their scores (sample_id, entropy), reference and held-out rows; staged tables."""

    cand: DataFrame
    scores: DataFrame
    ref: DataFrame
    test: DataFrame
    n: int

    @classmethod
    def build(cls, cand: DataFrame, scores: DataFrame, ref: DataFrame, test: DataFrame) -> Bench:
        spark = cand.sparkSession
        cand, test = stage(spark, cand, "cand"), stage(spark, test, "test")
        scores = stage(spark, scores.join(cand.select("sample_id"), "sample_id", "left_semi"), "scores")
        return cls(cand, scores, ref, test, scores.count())

    def rows(self, chosen: DataFrame, **tags) -> DataFrame:
        out = self.cand.join(chosen.select("sample_id"), "sample_id", "left_semi")
        return out.select(*[F.lit(v).alias(k) for k, v in tags.items()], "sample_id", "vec", "label")


def _union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def _measured(tagged: DataFrame, test: DataFrame, by: list[str]) -> DataFrame:
    """by, n, classes (with a row), evenness over them (0 for a single class), moment."""
    tagged = stage(tagged.sparkSession, tagged, "tagged")
    cells = tagged.groupBy(*by, "label").agg(F.count(F.lit(1)).alias("c"))
    n, k = F.sum("c"), F.count(F.lit(1))
    h = F.ln(n.cast("double")) - F.sum(F.col("c") * F.ln(F.col("c").cast("double"))) / n
    counts = cells.groupBy(*by).agg(n.alias("n"), k.alias("classes"), F.when(k > 1, h / F.ln(k.cast("double"))).otherwise(0.0).alias("evenness"))
    return counts.join(M.moment_distance(tagged, test, *by).select(*by, "moment"), by)


def two_stage(b: Bench, model: CentroidModel, rho_bp: int, keep_bp: int, assigned: DataFrame | None = None) -> DataFrame:
    """scene sample of the keep_bp share of highest entropy; assigned may hold all candidates' clusters already."""
    spark = b.cand.sparkSession
    survivors = b.scores if keep_bp >= 10_000 else prune_top_fraction(b.scores, keep_bp, b.n)
    if assigned is None:
        assigned = assign_clusters(b.cand.join(survivors.select("sample_id"), "sample_id", "left_semi"), model)
    else:
        assigned = assigned.join(survivors.select("sample_id"), "sample_id", "left_semi")
    return scene_sample(stage(spark, assigned, "assigned"), budget_of(b.n, rho_bp), model.k, ranks=False)


def stage1_sweep(b: Bench, keeps_bp: list[int]) -> DataFrame:
    """keep_bp, n, classes, moment, min_h"""
    kept = [(k, stage(b.cand.sparkSession, prune_top_fraction(b.scores, k, b.n), "kept")) for k in keeps_bp]
    floors = _union([s.agg(F.lit(k).alias("keep_bp"), F.min("entropy").alias("min_h")) for k, s in kept])
    return _measured(_union([b.rows(s, keep_bp=k) for k, s in kept]), b.test, ["keep_bp"]).join(floors, "keep_bp")


METHODS = ("random", "moderate", "cluster_nearest", "retrieval", "anchor", "entropy", "two_stage")


def select_by(b: Bench, method: str, budget: int, rho_bp: int, k: int, iters: int, model: CentroidModel, shared: dict | None = None) -> DataFrame:
    """shared, one for all budgets of a bench and model, keeps the tables that do not depend on the budget."""
    shared, spark = {} if shared is None else shared, b.cand.sparkSession

    def once(make: Callable):
        if method not in shared:
            shared[method] = make()
        return shared[method]

    if method == "random":
        return B.random_rows(b.cand, budget)
    if method == "moderate":
        return B.moderate_distance(b.cand, "label", budget, gaps=once(lambda: B.moderate_gaps(b.cand, "label")))
    if method == "cluster_nearest":
        return scene_sample(once(lambda: stage(spark, assign_clusters(b.cand, fit_centroids(b.cand, k, iters)), "assigned")), budget, k, ranks=False)
    if method == "retrieval":
        return B.best_retrieved(once(lambda: stage(spark, retrieved(b.cand, b.ref, 4), "retrieved")), budget)
    if method == "anchor":
        return B.anchor_stratified(b.cand, [F.col("label")], budget)
    if method == "entropy":
        return prune_top_fraction(b.scores, 10_000 - rho_bp, b.n)
    return two_stage(b, model, rho_bp, default_stage1_keep(rho_bp), once(lambda: stage(spark, assign_clusters(b.cand, model), "assigned")))


def compare_methods(b: Bench, rho_bp: int, k: int, iters: int, methods: tuple[str, ...] = METHODS) -> DataFrame:
    """method, n, classes, moment"""
    model = fit_centroids(b.ref, k, iters)
    parts = [b.rows(select_by(b, m, budget_of(b.n, rho_bp), rho_bp, k, iters, model), method=m) for m in methods]
    return _measured(_union(parts), b.test, ["method"])


def convergence_curves(b: Bench, rhos_bp: list[int], k: int, iters: int, batch: int, methods: tuple[str, ...]) -> DataFrame:
    """method ('rho:method'), step, n, moment"""
    model = fit_centroids(b.ref, k, iters)
    shared: dict = {}
    parts = [b.rows(select_by(b, m, budget_of(b.n, r), r, k, iters, model, shared), method=f"{r}:{m}") for r in rhos_bp for m in methods]
    return M.convergence(stage(b.cand.sparkSession, _union(parts), "curves"), b.test, batch)


def stage_grid(b: Bench, rhos_bp: list[int], p1s_bp: list[int], k: int, iters: int) -> DataFrame:
    """rho_bp, p1_bp, n, classes, moment; p1 equal to the kept share is stage I alone."""
    model = fit_centroids(b.ref, k, iters)
    assigned = stage(b.cand.sparkSession, assign_clusters(b.cand, model), "assigned")
    parts = [b.rows(two_stage(b, model, r, p, assigned), rho_bp=r, p1_bp=p) for r in rhos_bp for p in sorted({10_000 - r, *p1s_bp})]
    return _measured(_union(parts), b.test, ["rho_bp", "p1_bp"])


def ratio_sweep(b: Bench, rhos_bp: list[int], k: int, iters: int) -> DataFrame:
    """rho_bp, n, classes, moment"""
    model = fit_centroids(b.ref, k, iters)
    assigned = stage(b.cand.sparkSession, assign_clusters(b.cand, model), "assigned")
    parts = [b.rows(two_stage(b, model, r, default_stage1_keep(r), assigned), rho_bp=r) for r in rhos_bp]
    return _measured(_union(parts), b.test, ["rho_bp"])


@dataclass
class Source:
    """Rows that centroids are learnt on, with a fitting function of its own and a projection of rows and candidates."""

    data: DataFrame
    fit: Callable[[DataFrame], CentroidModel]
    project: Callable[[DataFrame], DataFrame]
    rounds: float  # passes over the rows that the fitting amounts to


def cluster_sources(b: Bench, sources: dict[str, DataFrame | Source], k: int, iters: int, rho_bp: int = 7000, timed: bool = False) -> DataFrame:
    """source, rows, products (T * rows * K * d), n, classes, evenness, moment (and seconds and shuffle_bytes of the clustering)."""
    spark, parts, facts = b.cand.sparkSession, [], []
    for name, data in sources.items():
        source = data if isinstance(data, Source) else Source(data, lambda rows: fit_centroids(rows, k, iters), lambda rows: rows, iters)
        rows = source.data.count()
        with M.CostReport(spark if timed else None) as cost:
            model = source.fit(source.project(source.data))
        facts.append((name, rows, round(rows * k * model.matrix.shape[1] * source.rounds), cost.seconds, cost.shuffle_bytes))
        keep = default_stage1_keep(rho_bp)
        survivors = b.scores if keep >= 10_000 else prune_top_fraction(b.scores, keep, b.n)
        cand = b.cand.join(survivors.select("sample_id"), "sample_id", "left_semi")
        parts.append(b.rows(two_stage(b, model, rho_bp, keep, assign_clusters(source.project(cand), model)), source=name))
    frame = spark.createDataFrame(facts, "source string, rows long, products long, seconds double, shuffle_bytes long")
    return _measured(_union(parts), b.test, ["source"]).join(frame if timed else frame.drop("seconds", "shuffle_bytes"), "source")


def k_sweep(b: Bench, ks: list[int], iters: int, rho_bp: int = 5000) -> DataFrame:
    """k, empty, rare (pools below quota), refill, moment, classes, n"""
    spark, parts, facts = b.cand.sparkSession, [], []
    budget = budget_of(b.n, rho_bp)
    for k in ks:
        model = fit_centroids(b.ref, k, iters)
        assigned = stage(spark, assign_clusters(b.cand, model), "assigned")
        picked = stage(spark, scene_sample(assigned, budget, k, ranks=False), "picked")
        pools = pool_sizes(assigned, k).agg(F.lit(k).alias("k"), F.count_if(F.col("n") == 0).alias("empty"), F.count_if(F.col("n") < equal_quota(budget, k)).alias("rare"))
        facts.append(pools.crossJoin(picked.agg(F.count_if(F.col("picked_by") == "refill").alias("refill"))))
        parts.append(b.rows(picked, k=k))
    return _measured(_union(parts), b.test, ["k"]).join(_union(facts), "k")


def class_vs_overcluster(b: Bench, k: int, iters: int) -> DataFrame:
    """kind, k, cohesion: mean similarity of candidates to their centroid under class means and under over-clustering."""
    from ..operators.centroids import class_centroids

    rows = class_centroids(b.ref, "label").orderBy("label").collect()  # a row for each class
    import numpy as np

    models = {"class": CentroidModel(np.array([r["centroid"] for r in rows])), "overcluster": fit_centroids(b.ref, k, iters)}
    return _union([assign_clusters(b.cand, m).agg(F.lit(name).alias("kind"), F.lit(m.k).alias("k"), F.avg("sim").alias("cohesion")) for name, m in models.items()])


def metric_agreement(results: DataFrame, a: str, others: list[str]) -> DataFrame:
    """(measure, n, spearman): rank correlation of a with each other measure over the result rows."""
    rank = lambda c: F.rank().over(Window.orderBy(c)).cast("double")  # noqa: E731  a row for each setting
    return _union([results.select(rank(a).alias("x"), rank(b).alias("y")).agg(F.lit(b).alias("measure"), F.count(F.lit(1)).alias("n"), F.corr("x", "y").alias("spearman")) for b in others])


def restoration_scores(b: Bench, rho_bp: int, k: int, iters: int, methods: tuple[str, ...] = METHODS) -> DataFrame:
    """method, moment, sr, sr_paired, sis, sis_paired, unsupported: the generation proxy beside both downstream proxies.

    Each of those is scored by the squared gap and by the paired distance of truth and guess; unsupported is the share of
    held-out rows whose condition the subset does not hold, which have no guess.
    """
    spark, model, rows, pairs = b.cand.sparkSession, fit_centroids(b.ref, k, iters), [], []
    for m in methods:
        own = stage(spark, b.rows(select_by(b, m, budget_of(b.n, rho_bp), rho_bp, k, iters, model), method=m), "rows")
        rows.append(own)
        for kind, found in (("sr", M.super_resolution(own, b.test)), ("sis", M.from_condition(own, b.test, "label"))):
            pairs.append(found.select(F.lit(m).alias("method"), F.lit(kind).alias("kind"), "truth", "guess"))
    both = stage(spark, _union(pairs), "pairs")
    gaps = both.groupBy("method").agg(*[F.avg(F.when(F.col("kind") == kind, M.square_gap(F.col("truth"), F.col("guess")))).alias(kind) for kind in ("sr", "sis")], F.avg(F.when(F.col("kind") == "sis", F.col("guess").isNull().cast("double"))).alias("unsupported"))
    paired = M.paired_feature_distance(both, "truth", "guess", 8, "method", "kind").groupBy("method").pivot("kind", ["sr", "sis"]).agg(F.first("paired"))
    paired = paired.select("method", F.col("sr").alias("sr_paired"), F.col("sis").alias("sis_paired"))
    moments = M.moment_distance(stage(spark, _union(rows), "tagged"), b.test, "method").select("method", "moment")
    return moments.join(gaps, "method").join(paired, "method")


def scale_transfer(benches: dict[str, Bench], rho_bp: int, k: int, iters: int, methods: tuple[str, ...] = ("random", "entropy", "two_stage")) -> DataFrame:
    """scale, method, n, classes, evenness, moment: the same comparison on pools of several sizes."""
    parts = []
    for name, b in benches.items():
        model = fit_centroids(b.ref, k, iters)
        rows = [b.rows(select_by(b, m, budget_of(b.n, rho_bp), rho_bp, k, iters, model), scale=name, method=m) for m in methods]
        parts.append(_measured(_union(rows), b.test, ["scale", "method"]))
    return _union(parts)


def web_filter(pages: DataFrame, min_chars: int, tau: float) -> DataFrame:
    """(sample_id, n_chars, entropy): tags stripped, size and entropy floors, one page of each equal text."""
    text = F.trim(F.regexp_replace(F.regexp_replace("html", "<[^>]*>", " "), "[ \\n\\r\\t]+", " "))
    rows = pages.select(F.col("page_id").alias("sample_id"), text.alias("payload")).withColumn("n_chars", F.length("payload").cast("long")).filter(F.col("n_chars") >= min_chars)
    scored = rows.join(sample_entropy(rows, BYTES), "sample_id").filter(F.col("entropy") >= tau)
    return scored.groupBy("payload").agg(F.min(F.struct("sample_id", "n_chars", "entropy")).alias("r")).select("r.*")


def part_profiles(part: DataFrame, lineitem: DataFrame) -> DataFrame:
    """(sample_id, entropy, vec, label): quantity histogram of each part over 50 levels; counted with map-side combine."""
    counts = lineitem.groupBy("l_partkey", F.col("l_quantity").cast("int").alias("q")).agg(F.count(F.lit(1)).alias("n"))
    hist = counts.groupBy("l_partkey").agg(F.map_from_entries(F.collect_list(F.struct("q", "n"))).alias("m"), F.sum("n").cast("double").alias("t"), F.sum(F.col("n") * F.ln(F.col("n").cast("double"))).alias("s"))  # 50 levels at most
    vec = F.transform(F.sequence(F.lit(1), F.lit(50)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0)).cast("double"))
    rows = hist.select(F.col("l_partkey").alias("sample_id"), F.greatest(F.lit(0.0), F.ln("t") - F.col("s") / F.col("t")).alias("entropy"), vec.alias("vec"))
    return rows.join(part.select(F.col("p_partkey").alias("sample_id"), F.col("p_type").alias("label")), "sample_id")


def population_slices(scores: DataFrame, strata: DataFrame, keep_bp: int) -> DataFrame:
    """stratum, n, kept, mean_h: how a global entropy cut falls on sub-populations."""
    n = scores.count()
    kept = prune_top_fraction(scores, keep_bp, n).select("sample_id", F.lit(1).alias("k"))
    rows = scores.join(strata.select("sample_id", "stratum"), "sample_id").join(kept, "sample_id", "left")
    return rows.groupBy("stratum").agg(F.count(F.lit(1)).alias("n"), F.count("k").alias("kept"), F.avg("entropy").alias("mean_h"))


