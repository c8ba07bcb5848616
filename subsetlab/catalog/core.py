"""Stage I, stage II, sampling and kernels."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import levels as L
from ..functions import vectors as V
from ..operators import assign as A
from ..operators import centroids as C
from ..operators import entropy as H
from ..operators import features
from ..operators import sampling as S
from ..operators.select import SelectionPlanner, top_n, top_q_per_group
from ..plans.pipeline import prune
from ..schemas import CONVERSATIONS, EMBEDDINGS, PAGES, VECTOR
from ..sources.tables import load_samples, stage, table
from . import sqlparts as P
from .inputs import BANK_LABELS, ITERS, K_D, K_E, bank, d_pool, d_pool_samples, d_ref, docs, e_all, e_pool, e_ref, e_scores
from .registry import Registry

R = Registry()
FORCE = SelectionPlanner(sort_rows=0, window_rows=0, boundary_rows=20)


def r6(df, *cols):
    return df.select(*[F.round(c, 6).alias(c) if c in cols else F.col(c) for c in df.columns])


def _h(df):
    return r6(df, "entropy")


H_OUT = "SELECT id AS sample_id, round(h, 6) AS entropy FROM "


@R.add("s1_byte_histogram", """SELECT doc_id AS sample_id, lv AS level, count(*) AS n, CAST(sum(count(*)) OVER (PARTITION BY doc_id) AS BIGINT) AS total
FROM (SELECT doc_id, unnest(regexp_extract_all(hex(encode(text)), '..')) AS lv FROM documents) GROUP BY doc_id, lv""")
def _(spark, d):
    return H.level_histogram(docs(spark, d), L.byte_levels(F.col("payload"))).drop("prob")


@R.add("s1_doc_entropy", P.with_(P.DOC_H, select=H_OUT + "dh"))
def _(spark, d):
    return _h(H.sample_entropy(docs(spark, d)))


@R.add("s1_page_entropy", P.with_(P.byte_h("ph", "pages", "page_id", "html"), select=H_OUT + "ph"))
def _(spark, d):
    return _h(H.sample_entropy(load_samples(spark, d, PAGES)))


@R.add("s1_conv_entropy", P.with_("c AS (SELECT conv_id * 1000 + turn AS cid, text FROM conversations)", P.byte_h("ch", "c", "cid", "text"), select=H_OUT + "ch"))
def _(spark, d):
    return _h(H.sample_entropy(load_samples(spark, d, CONVERSATIONS)))


@R.add("s1_vec_entropy", P.with_(P.E, P.E_H, select=H_OUT + "eh"))
def _(spark, d):
    return _h(e_scores(spark, d))


_BANDS = "g AS (SELECT id, list_transform(range(1, 17), lambda p: (v[p] + v[p + 16] + v[p + 32] + v[p + 48]) / 4) AS w FROM e)"


@R.add("s1_vec_entropy_4band", P.with_(P.E, _BANDS, f"glv AS (SELECT id, unnest({P.quantized('w', 16, '-0.25', '0.25')}) AS lv FROM g)", P.level_h("gh", "glv", "id", "lv"), select=H_OUT + "gh"))
def _(spark, d):
    bands = L.cut_bands(F.col("vec"), 4, 16)
    gray = F.zip_with(F.zip_with(bands[0], bands[1], lambda a, b: a + b), bands[2], lambda a, b: a + b)
    gray = F.transform(F.zip_with(gray, bands[3], lambda a, b: a + b), lambda x: x / 4)
    return _h(H.sample_entropy(e_all(spark, d).select("sample_id", gray.alias("payload")), VECTOR, lo=-0.25, hi=0.25))


@R.add("s1_gray_luma", P.with_(P.E, select="SELECT id AS sample_id, list_transform(range(1, 17), lambda p: round(v[p] * 0.299 + v[p + 16] * 0.587 + v[p + 32] * 0.114, 6)) AS gray FROM e"))
def _(spark, d):
    gray = L.to_gray(L.cut_bands(F.col("vec"), 3, 16), L.LUMA)
    return e_all(spark, d).select("sample_id", V.rounded(gray).alias("gray"))


@R.add("s1_vec_entropy_minmax", P.with_(P.E, f"mlv AS (SELECT id, unnest({P.quantized('v', 16, 'list_min(v)', 'list_max(v)')}) AS lv FROM e)", P.level_h("mh", "mlv", "id", "lv"), select=H_OUT + "mh"))
def _(spark, d):
    return _h(H.sample_entropy(load_samples(spark, d, EMBEDDINGS), VECTOR, lo=None, hi=None))


@R.add("s1_entropy_base2_normalized", P.with_(P.DOC_H, select="SELECT id AS sample_id, round(h / ln(2), 6) AS bits, round(h / ln(256), 6) AS share FROM dh"))
def _(spark, d):
    two, share = H.sample_entropy(docs(spark, d), base=2.0), H.sample_entropy(docs(spark, d), normalized=True)
    return two.select("sample_id", F.round("entropy", 6).alias("bits")).join(share.select("sample_id", F.round("entropy", 6).alias("share")), "sample_id")


@R.add("s1_sql_engine_entropy", P.with_(P.DOC_H, select=H_OUT + "dh"))
def _(spark, d):
    return _h(H.sample_entropy(docs(spark, d), engine="sql"))


@R.add("s1_threshold", P.with_(P.DOC_H, select=H_OUT + "dh WHERE h >= 2.9"))
def _(spark, d):
    return _h(H.prune_by_threshold(H.sample_entropy(docs(spark, d)), 2.9))


@R.add("s1_top_fraction", P.with_(P.DOC_H, P.top_h("t", "dh", "SELECT count(*) * 3000 // 10000 FROM dh"), select=H_OUT + "t"))
def _(spark, d):
    return _h(H.prune_top_fraction(stage(spark, H.sample_entropy(docs(spark, d)), "h"), 3000))


@R.add("s1_nested_subsets", P.with_(P.DOC_H, "o AS (SELECT *, row_number() OVER (ORDER BY round(h, 9) DESC, id) AS rk, count(*) OVER () AS n FROM dh)", "k AS (SELECT unnest([1000, 1500, 3000, 5000, 7000, 10000]) AS keep_bp)", select="SELECT keep_bp, count(*) AS n, round(min(h), 6) AS min_entropy, CAST(sum(id) AS BIGINT) AS id_sum FROM o JOIN k ON rk <= n * keep_bp // 10000 GROUP BY keep_bp"))
def _(spark, d):
    scored = stage(spark, H.sample_entropy(docs(spark, d)), "h")
    n, out = scored.count(), None
    for bp in (1000, 1500, 3000, 5000, 7000, 10000):
        part = H.prune_top_fraction(scored, bp, n).agg(F.lit(bp).alias("keep_bp"), F.count(F.lit(1)).alias("n"), F.round(F.min("entropy"), 6).alias("min_entropy"), F.sum("sample_id").alias("id_sum"))
        out = part if out is None else out.unionByName(part)
    return out


@R.add("s1_cutoff", P.with_(P.DOC_H, P.top_h("t", "dh", "SELECT count(*) * 3000 // 10000 FROM dh"), select="SELECT round(min(h), 6) AS cutoff FROM t"))
def _(spark, d):
    scored = stage(spark, H.sample_entropy(docs(spark, d)), "h")
    return spark.createDataFrame([(H.entropy_cutoff(scored, 3000),)], "cutoff double").select(F.round("cutoff", 6).alias("cutoff"))


@R.add("s1_cutoff_sketch", P.with_(P.DOC_H, select="SELECT count(*) AS n, TRUE AS within FROM dh"))
def _(spark, d):
    """The sketch's threshold keeps the wanted share to within a hundredth of the rows."""
    scored = stage(spark, H.sample_entropy(docs(spark, d)), "h")
    kept = F.count_if(F.col("entropy") >= H.entropy_cutoff(scored, 3000, exact=False)) / F.count(F.lit(1))
    return scored.agg(F.count(F.lit(1)).alias("n"), (F.abs(kept - 0.3) <= 0.01).alias("within"))


@R.add("s1_reject_report", P.with_(P.DOC_H, select="""SELECT CASE WHEN length(text) = 0 THEN 'empty' WHEN round(h, 9) = 0 THEN 'constant' WHEN h < 2.9 THEN 'low_variation' ELSE 'kept' END AS reason, count(*) AS n
FROM dh JOIN documents ON doc_id = id GROUP BY 1"""))
def _(spark, d):
    return H.explain_rejects(docs(spark, d), H.sample_entropy(docs(spark, d)), 2.9)


@R.add("s1_event_type_entropy", P.with_(P.level_h("h", "events", "user_id", "event_type"), select="SELECT user_id, round(h, 6) AS entropy FROM h"))
def _(spark, d):
    return _h(H.group_entropy(table(spark, d, "events"), ["user_id"], "event_type"))


@R.add("s1_quantity_entropy", P.with_(P.level_h("h", "lineitem", "l_partkey", "l_quantity"), select="SELECT l_partkey, round(h, 6) AS entropy FROM h"))
def _(spark, d):
    return _h(H.group_entropy(table(spark, d, "lineitem"), ["l_partkey"], "l_quantity"))


@R.add("s1_tiled_entropy", P.with_("t AS (SELECT source, unnest(regexp_extract_all(hex(encode(text)), '..')) AS lv FROM documents)", P.level_h("h", "t", "source", "lv"), select="SELECT source, round(h, 6) AS entropy FROM h"))
def _(spark, d):
    tiles = table(spark, d, "documents").select("source", F.explode(L.byte_levels(F.col("text"))).alias("lv"))
    return _h(H.group_entropy(tiles, ["source"], "lv"))


# Stage II


@R.add("s2_doc_features", P.with_(P.DOC_VEC, select="SELECT id AS sample_id, list_transform(z, lambda x: round(x, 6)) AS vec FROM dz"))
def _(spark, d):
    return features.hashed_tokens(docs(spark, d)).filter("vec IS NOT NULL").select("sample_id", F.transform("vec", lambda x: F.round(x, 6)).alias("vec"))


@R.add("s2_level_profile", P.with_(P.E, f"q AS (SELECT id, {P.quantized('v')} AS lv FROM e)", select="SELECT id AS sample_id, list_transform(range(16), lambda k: round(len(list_filter(lv, lambda x: x = k)) / len(lv), 6)) AS vec FROM q"))
def _(spark, d):
    return features.level_profile(load_samples(spark, d, EMBEDDINGS)).select("sample_id", F.transform("vec", lambda x: F.round(x, 6)).alias("vec"))


@R.add("s2_normalize", P.with_(P.E, P.Z, select="SELECT id AS sample_id, list_transform(z, lambda x: round(x, 6)) AS vec FROM z"))
def _(spark, d):
    return features.normalized(features.identity(load_samples(spark, d, EMBEDDINGS))).select("sample_id", V.rounded(F.col("vec")).alias("vec"))


@R.add("s2_bank_composition", "SELECT 'bank' || CAST(label // 2 + 1 AS VARCHAR) AS bank, count(*) AS n, count(DISTINCT label) AS classes FROM embeddings WHERE vec_id % 5 < 2 GROUP BY 1")
def _(spark, d):
    banks = {f"bank{i}": bank(spark, d, labels) for i, labels in enumerate(BANK_LABELS, 1)}
    return C.reference_bank(banks).groupBy("bank").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("class_label").alias("classes"))


@R.add("s2_class_centroids", P.with_(P.E, P.Z, P.REF, "s AS (SELECT label, list(s ORDER BY pos) AS v FROM (SELECT label, pos, sum(x) AS s FROM (SELECT label, unnest(z) AS x, generate_subscripts(z, 1) AS pos FROM ref) GROUP BY ALL) GROUP BY label)", select=f"SELECT label, list_transform({P.unit('v')}, lambda x: round(x, 6)) AS centroid FROM s"))
def _(spark, d):
    return C.class_centroids(e_ref(spark, d), "label").select("label", F.transform("centroid", lambda x: F.round(x, 6)).alias("centroid"))


E_MODEL = (P.E, P.Z, P.REF, P.POOL, P.kmeans("m", "ref", K_E, ITERS))
D_MODEL = (P.DOC_VEC, P.D_REF, P.D_POOL, P.kmeans("m", "dref", K_D, ITERS))


def e_model(spark, d, k=K_E, **kw):
    return C.fit_centroids(e_ref(spark, d), k, ITERS, **kw)


def _centroids(spark, model):
    return model.frame(spark).select("cluster_id", F.transform("centroid", lambda x: F.round(x, 6)).alias("centroid"))


@R.add("s2_spherical_kmeans", P.with_(*E_MODEL, select="SELECT k AS cluster_id, list_transform(z, lambda x: round(x, 6)) AS centroid FROM m_c"))
def _(spark, d):
    return _centroids(spark, e_model(spark, d))


@R.add("s2_kmeans_farthest_first", P.with_(P.E, P.Z, P.REF, P.farthest("ff", "ref", 8), P.kmeans("m", "ref", 8, ITERS, "ff"), select="SELECT k AS cluster_id, list_transform(z, lambda x: round(x, 6)) AS centroid FROM m_c"))
def _(spark, d):
    return _centroids(spark, e_model(spark, d, 8, init="farthest_first"))


@R.add("s2_kmeans_hash_order", P.with_(P.E, P.Z, P.REF, P.kmeans("m", "ref", K_E, ITERS, order="md5('42:' || CAST(id AS VARCHAR)), id"), select="SELECT k AS cluster_id, list_transform(z, lambda x: round(x, 6)) AS centroid FROM m_c"))
def _(spark, d):
    return _centroids(spark, e_model(spark, d, init="hash_order"))


@R.add("s2_kmeans_ml")
def _(spark, d):
    return _centroids(spark, C.fit_library(e_ref(spark, d), K_E))


@R.add("s2_minibatch_kmeans", P.with_(P.E, P.Z, P.POOL, P.projected("pp", "pool", 64, 8), P.minibatch("m", "pp", K_E, 5), select="SELECT k AS cluster_id, list_transform(z, lambda x: round(x, 6)) AS centroid FROM m_c"))
def _(spark, d):
    return _centroids(spark, C.fit_minibatch(features.random_projection(e_pool(spark, d), 64, 8), K_E, 5))


def _assigned(df):
    return r6(df, "sim")


@R.add("s2_assign_cosine", P.with_(*E_MODEL, P.assign("a", "pool", "m_c"), select="SELECT id AS sample_id, k AS cluster_id, round(sim, 6) AS sim FROM a"))
def _(spark, d):
    return _assigned(A.assign_clusters(e_pool(spark, d), e_model(spark, d)))


@R.add("s2_assign_sql_engine", P.with_(*E_MODEL, P.assign("a", "pool", "m_c"), select="SELECT id AS sample_id, k AS cluster_id, round(sim, 6) AS sim FROM a"))
def _(spark, d):
    return _assigned(A.assign_clusters(e_pool(spark, d), e_model(spark, d), engine="sql"))


@R.add("s2_assign_inner", P.with_(*E_MODEL, "big AS (SELECT id, list_transform(v, lambda x: x * (1 + id % 3)) AS z FROM pool)", P.assign("a", "big", "m_c"), select="SELECT id AS sample_id, k AS cluster_id, round(sim, 6) AS sim FROM a"))
def _(spark, d):
    scaled = e_pool(spark, d).withColumn("vec", F.transform("vec", lambda x: x * (1 + F.col("sample_id") % 3)))
    return _assigned(A.assign_clusters(scaled, e_model(spark, d), "inner"))


@R.add("s2_similarity_matrix", P.with_(*E_MODEL, select="SELECT p.id AS sample_id, c.k AS cluster_id, round(list_dot_product(p.z, c.z), 6) AS sim FROM pool p CROSS JOIN m_c c"))
def _(spark, d):
    return _assigned(A.similarity_matrix(e_pool(spark, d), e_model(spark, d)))


_TOP3 = "x AS (SELECT p.id, c.k, list_dot_product(p.z, c.z) AS sim, row_number() OVER (PARTITION BY p.id ORDER BY round(list_dot_product(p.z, c.z), 9) DESC, c.k) AS rk FROM pool p CROSS JOIN m_c c)"


@R.add("s2_assign_top3", P.with_(*E_MODEL, _TOP3, select="SELECT id AS sample_id, rk AS rank, k AS cluster_id, round(sim, 6) AS sim FROM x WHERE rk <= 3"))
def _(spark, d):
    return _assigned(A.assign_topk(e_pool(spark, d), e_model(spark, d), 3))


@R.add("s2_margins", P.with_(*E_MODEL, _TOP3, select="SELECT id AS sample_id, round(max(sim) - min(sim), 6) AS margin FROM x WHERE rk <= 2 GROUP BY id"))
def _(spark, d):
    return r6(A.margins(e_pool(spark, d), e_model(spark, d)), "margin")


@R.add("s2_pool_sizes", P.with_(*D_MODEL, P.assign("a", "dpool", "m_c"), select="SELECT c.k AS cluster_id, count(a.id) AS n FROM m_c c LEFT JOIN a ON a.k = c.k GROUP BY c.k"))
def _(spark, d):
    return A.pool_sizes(A.assign_clusters(d_pool(spark, d), d_model(spark, d)), K_D)


def d_model(spark, d):
    return C.fit_centroids(d_ref(spark, d).filter("vec IS NOT NULL"), K_D, ITERS)


@R.add("s2_doc_assign", P.with_(*D_MODEL, P.assign("a", "dpool", "m_c"), select="SELECT id AS sample_id, k AS cluster_id, round(sim, 6) AS sim FROM a"))
def _(spark, d):
    return _assigned(A.assign_clusters(d_pool(spark, d), d_model(spark, d)).filter("cluster_id IS NOT NULL"))


# Sampling

E_ASSIGNED = (*E_MODEL, P.assign("a", "pool", "m_c"))
HALF = "SELECT count(*) * 5000 // 10000 FROM pool"


def e_assigned(spark, d, k=K_E):
    return stage(spark, A.assign_clusters(e_pool(spark, d), e_model(spark, d, k)), "assigned")


def _scene(df):
    return r6(df, "sim")


@R.add("s3_quota", P.with_(*E_ASSIGNED, select=f"SELECT id AS sample_id, k AS cluster_id, round(sim, 6) AS sim FROM (SELECT *, row_number() OVER (PARTITION BY k ORDER BY round(sim, 9) DESC, id) AS rk FROM a) WHERE rk <= ({HALF}) // {K_E}"))
def _(spark, d):
    a = e_assigned(spark, d)
    return _assigned(S.take_quota(a, S.equal_quota(a.count() * 5000 // 10000, K_E)))


@R.add("s3_scene_sample", P.with_(*E_ASSIGNED, P.scene("s", "a", HALF, K_E), select=P.OUT + "s"))
def _(spark, d):
    a = e_assigned(spark, d)
    return _scene(S.scene_sample(a, a.count() * 5000 // 10000, K_E))


@R.add("s3_scene_sample_single_plan", P.with_(*E_ASSIGNED, P.scene("s", "a", HALF, K_E), select=P.OUT + "s"))
def _(spark, d):
    a = e_assigned(spark, d)
    return _scene(S.scene_sample_single_plan(a, a.count() * 5000 // 10000, K_E))


@R.add("s3_refill", P.with_(*E_ASSIGNED, P.scene("s", "a", HALF, K_E), select=P.OUT + "s WHERE picked_by = 'refill'"))
def _(spark, d):
    a = e_assigned(spark, d)
    return _scene(S.refill(a, a.count() * 5000 // 10000, K_E))


@R.add("s3_scene_sample_b_lt_k", P.with_(*E_ASSIGNED, P.scene("s", "a", "7", K_E), select=P.OUT + "s"))
def _(spark, d):
    return _scene(S.scene_sample(e_assigned(spark, d), 7, K_E))


@R.add("s3_scene_sample_rare", P.with_(*D_MODEL, P.assign("a", "dpool", "m_c"), P.scene("s", "a", "SELECT count(*) * 5000 // 10000 FROM a", K_D), select=P.OUT + "s"))
def _(spark, d):
    a = stage(spark, A.assign_clusters(d_pool(spark, d), d_model(spark, d)).filter("cluster_id IS NOT NULL"), "a")
    return _scene(S.scene_sample(a, a.count() * 5000 // 10000, K_D))


@R.add("s3_scene_sample_b_ge_n", P.with_(*E_ASSIGNED, P.scene("s", "a", "SELECT count(*) + 50 FROM a", K_E), select=P.OUT + "s"))
def _(spark, d):
    a = e_assigned(spark, d)
    return _scene(S.scene_sample(a, a.count() + 50, K_E))


_POOLS = "p AS MATERIALIZED (SELECT c.k, count(a.id) AS n FROM m_c c LEFT JOIN a ON a.k = c.k GROUP BY c.k)"
for _policy, _weight in (("equal", "1.0"), ("proportional", "CAST(n AS DOUBLE)"), ("sqrt", "sqrt(CAST(n AS DOUBLE))")):

    @R.add(f"s3_alloc_{_policy}", P.with_(*E_ASSIGNED, _POOLS, select=f"SELECT k AS cluster_id, n, CAST(least(n, floor(round(CAST(({HALF}) AS DOUBLE) * {_weight} / sum({_weight}) OVER (), 9))) AS BIGINT) AS quota FROM p"))
    def _(spark, d, policy=_policy):
        a = e_assigned(spark, d)
        return S.allocate(A.pool_sizes(a, K_E), a.count() * 5000 // 10000, policy)


@R.add("s3_alloc_waterfill", P.with_(*E_ASSIGNED, _POOLS, f"b AS (SELECT ({HALF}) AS b)", "g AS (SELECT unnest(range(CAST((SELECT max(n) FROM p) AS BIGINT) + 1)) AS l)", "lv AS (SELECT max(l) AS l FROM (SELECT l, sum(least(n, l)) AS s FROM g, p GROUP BY l), b WHERE s <= b)", "x AS (SELECT b - (SELECT sum(least(n, l)) FROM p, lv) AS extra FROM b)", select="SELECT k AS cluster_id, n, CAST(least(n, l) + CASE WHEN n > l AND row_number() OVER (PARTITION BY n > l ORDER BY k) <= extra THEN 1 ELSE 0 END AS BIGINT) AS quota FROM p, lv, x"))
def _(spark, d):
    a = e_assigned(spark, d)
    return S.allocate(A.pool_sizes(a, K_E), a.count() * 5000 // 10000, "waterfill")


_ORDER = {"farthest": "round(sim, 9), id", "random": P.hash_order("id") + ", id"}
for _name, _by in _ORDER.items():

    @R.add(f"s3_order_{_name}", P.with_(*E_ASSIGNED, select=f"SELECT id AS sample_id, k AS cluster_id, round(sim, 6) AS sim FROM (SELECT *, row_number() OVER (PARTITION BY k ORDER BY {_by}) AS rk FROM a) WHERE rk <= 5"))
    def _(spark, d, name=_name):
        return _assigned(S.take_quota(e_assigned(spark, d), 5, name))


@R.add("s3_order_median", P.with_(*E_ASSIGNED, "g AS (SELECT *, round(abs(round(sim, 9) - median(round(sim, 9)) OVER (PARTITION BY k)), 9) AS gap FROM a)", select="SELECT id AS sample_id, k AS cluster_id, round(sim, 6) AS sim FROM (SELECT *, row_number() OVER (PARTITION BY k ORDER BY gap, id) AS rk FROM g) WHERE rk <= 5"))
def _(spark, d):
    return _assigned(S.take_quota(e_assigned(spark, d), 5, "median"))


def two_stage_sql(rho: int, keep: int, rows: str, model: tuple, h: str, k: int) -> tuple[str, ...]:
    n = f"SELECT count(*) FROM {rows} JOIN {h} USING (id)"
    return (*model, P.top_h("s1", f"(SELECT id, h, z FROM {rows} JOIN {h} USING (id))", f"({n}) * {keep} // 10000"), P.assign("a", "s1", "m_c"), P.scene("s", "a", f"({n}) * {10000 - rho} // 10000", k))


@R.add("s3_two_stage_vec", P.with_(*two_stage_sql(8500, 3000, "pool", (*E_MODEL, P.E_H), "eh", K_E), select=P.OUT + "s"))
def _(spark, d):
    pool = e_pool(spark, d)
    scored = e_scores(spark, d).join(pool.select("sample_id"), "sample_id", "left_semi")
    return _scene(prune(scored, pool, e_model(spark, d), 8500).selected)


@R.add("s3_two_stage_doc", P.with_(*two_stage_sql(8500, 3000, "dpool", (*D_MODEL, P.DOC_H), "dh", K_D), select=P.OUT + "s"))
def _(spark, d):
    samples = d_pool_samples(spark, d)
    vectors = stage(spark, features.hashed_tokens(samples), "vectors").filter("vec IS NOT NULL")
    scored = H.sample_entropy(samples).join(vectors.select("sample_id"), "sample_id", "left_semi")
    return _scene(prune(scored, vectors, d_model(spark, d), 8500).selected)


@R.add("s3_stage1_only", P.with_(P.E, P.Z, P.POOL, P.E_H, P.top_h("s", "(SELECT id, h FROM pool JOIN eh USING (id))", "SELECT count(*) * 1500 // 10000 FROM pool"), select="SELECT id AS sample_id, 'entropy' AS picked_by FROM s"))
def _(spark, d):
    pool = e_pool(spark, d)
    scored = e_scores(spark, d).join(pool.select("sample_id"), "sample_id", "left_semi")
    return prune(scored, pool, None, 8500, stage2=False).selected.select("sample_id", "picked_by")


@R.add("s3_stage2_only", P.with_(*E_ASSIGNED, P.scene("s", "a", "SELECT count(*) * 1500 // 10000 FROM pool", K_E), select=P.OUT + "s"))
def _(spark, d):
    pool = e_pool(spark, d)
    scored = e_scores(spark, d).join(pool.select("sample_id"), "sample_id", "left_semi")
    return _scene(prune(scored, pool, e_model(spark, d), 8500, stage1_keep_bp=10_000).selected)


# Kernels, forced onto the histogram path


@R.add("s4_top_n_exact", "SELECT p_partkey AS sample_id, p_retailprice AS score FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 700")
def _(spark, d):
    rows = table(spark, d, "part").select(F.col("p_partkey").alias("sample_id"), F.col("p_retailprice").alias("score"))
    return top_n(rows, 700, "score", "sample_id", FORCE)


@R.add("s4_top_n_ties", "SELECT p_partkey AS sample_id, p_size AS score FROM part ORDER BY p_size DESC, p_partkey LIMIT 333")
def _(spark, d):
    rows = table(spark, d, "part").select(F.col("p_partkey").alias("sample_id"), F.col("p_size").alias("score"))
    return top_n(rows, 333, "score", "sample_id", FORCE)


@R.add("s4_top_q_exact", "SELECT sample_id, grp, score FROM (SELECT p_partkey AS sample_id, p_type AS grp, p_retailprice AS score, row_number() OVER (PARTITION BY p_type ORDER BY p_retailprice DESC, p_partkey) AS rk FROM part) WHERE rk <= 60")
def _(spark, d):
    rows = table(spark, d, "part").select(F.col("p_partkey").alias("sample_id"), F.col("p_type").alias("grp"), F.col("p_retailprice").alias("score"))
    return top_q_per_group(rows, "grp", 60, "score", "sample_id", FORCE)


