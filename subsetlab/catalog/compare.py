"""Baselines and measures."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import baselines as B
from ..operators import centroids as C
from ..operators import entropy as H
from ..operators import features
from ..operators import measures as M
from ..operators import sampling as S
from ..operators.pairs import drop_near_copies
from ..sources.tables import stage, table
from . import sqlparts as P
from .core import E_ASSIGNED, HALF, e_assigned, e_model, r6
from .inputs import BANK_LABELS, ITERS, K_E, bank, docs, e_all, e_candidates, e_pool, e_ref, e_scores, e_test
from .registry import Registry

R = Registry()


# Selections in SQL: each gives name(id)


def sel_random(name: str, rows: str, budget: str) -> str:
    return f"{name} AS MATERIALIZED (SELECT id FROM {rows} ORDER BY {P.hash_order('id')}, id LIMIT ({budget}))"


def sel_moderate(name: str, rows: str, budget: str) -> str:
    return f"""{name}_s AS (SELECT label, list(s ORDER BY pos) AS v FROM (SELECT label, pos, sum(x) AS s FROM (SELECT label, unnest(z) AS x, generate_subscripts(z, 1) AS pos FROM {rows}) GROUP BY ALL) GROUP BY label),
{name}_c AS (SELECT label, {P.unit('v')} AS c FROM {name}_s),
{name}_d AS MATERIALIZED (SELECT id, label, round(1 - list_dot_product(z, c), 9) AS dist FROM {rows} JOIN {name}_c USING (label)),
{name}_g AS (SELECT id, label, round(abs(dist - median(dist) OVER (PARTITION BY label)), 9) AS gap, count(*) OVER (PARTITION BY label) AS n FROM {name}_d),
{name}_o AS (SELECT *, row_number() OVER (PARTITION BY label ORDER BY gap, id) <= ({budget}) * n // (SELECT count(*) FROM {rows}) AS first FROM {name}_g),
{name} AS MATERIALIZED (SELECT id, gap FROM {name}_o ORDER BY CASE WHEN first THEN 0 ELSE 1 END, gap, id LIMIT ({budget}))"""


def sel_cluster(name: str, rows: str, budget: str, k: int = K_E) -> str:
    return ",\n".join([P.kmeans(f"{name}_m", rows, k, ITERS), P.assign(f"{name}_a", rows, f"{name}_m_c"), P.scene(name, f"{name}_a", budget, k)])


def sel_retrieval(name: str, rows: str, budget: str, m: int = 4) -> str:
    return f"""{name}_x AS MATERIALIZED (SELECT r.id AS rid, p.id, round(list_dot_product(r.z, p.z), 9) AS sim, list_dot_product(r.z, p.z) AS raw FROM ref r CROSS JOIN {rows} p),
{name}_h AS (SELECT DISTINCT id FROM (SELECT id, row_number() OVER (PARTITION BY rid ORDER BY sim DESC, id) AS rk FROM {name}_x) WHERE rk <= {m}),
{name}_b AS (SELECT id, max(raw) AS best FROM {name}_x GROUP BY id),
{name} AS MATERIALIZED (SELECT id, best FROM {name}_b ORDER BY CASE WHEN id IN (SELECT id FROM {name}_h) THEN 0 ELSE 1 END, round(best, 9) DESC, id LIMIT ({budget}))"""


def sel_anchor(name: str, rows: str, stratum: str, budget: str) -> str:
    return f"""{name}_o AS (SELECT id, {stratum} AS stratum, row_number() OVER (PARTITION BY {stratum} ORDER BY {P.hash_order('id')}, id) <= ({budget}) // (SELECT count(DISTINCT {stratum}) FROM {rows}) AS first FROM {rows}),
{name} AS MATERIALIZED (SELECT id, stratum FROM {name}_o ORDER BY CASE WHEN first THEN 0 ELSE 1 END, {P.hash_order('id')}, id LIMIT ({budget}))"""


def sel_entropy(name: str, rows: str, budget: str) -> str:
    return P.top_h(name, f"(SELECT id, h FROM {rows} JOIN eh USING (id))", budget)


BASE = (P.E, P.Z, P.REF, P.POOL, P.E_H)
B30 = "SELECT count(*) * 3000 // 10000 FROM pool"


def _b30(spark, d):
    return e_pool(spark, d).count() * 3000 // 10000


@R.add("bl_full", "SELECT vec_id AS sample_id FROM embeddings")
def _(spark, d):
    return B.full(e_all(spark, d))


@R.add("bl_random", P.with_(*BASE, sel_random("s", "pool", B30), select="SELECT id AS sample_id FROM s"))
def _(spark, d):
    return B.random_rows(e_pool(spark, d), _b30(spark, d))


@R.add("bl_moderate", P.with_(*BASE, sel_moderate("s", "pool", B30), select="SELECT id AS sample_id, round(gap, 6) AS gap FROM s"))
def _(spark, d):
    return r6(B.moderate_distance(e_pool(spark, d), "label", _b30(spark, d)), "gap")


@R.add("bl_cluster_nearest", P.with_(*BASE, sel_cluster("s", "pool", B30), select=P.OUT + "s"))
def _(spark, d):
    return r6(B.cluster_nearest(e_pool(spark, d), K_E, _b30(spark, d), ITERS), "sim")


@R.add("bl_retrieval_knn", P.with_(*BASE, sel_retrieval("s", "pool", B30), select="SELECT id AS sample_id, round(best, 6) AS best FROM s"))
def _(spark, d):
    return r6(B.retrieval_nearest(e_pool(spark, d), e_ref(spark, d), _b30(spark, d)), "best")


COPY = 0.5  # similarity of near copies among these vectors


@R.add("bl_retrieval_curated", P.with_(*BASE, f"near AS (SELECT DISTINCT b.id FROM pool a JOIN pool b ON a.id < b.id AND round(list_dot_product(a.z, b.z), 9) >= {COPY})", "own AS MATERIALIZED (SELECT * FROM pool WHERE id NOT IN (SELECT id FROM near))", sel_retrieval("s", "own", B30), select="SELECT id AS sample_id, round(best, 6) AS best FROM s"))
def _(spark, d):
    """Near copies leave the pool before the curated rows retrieve from it."""
    return r6(B.retrieval_nearest(e_pool(spark, d), e_ref(spark, d), _b30(spark, d), copies=COPY), "best")


@R.add("bl_near_copies", P.with_(P.E, P.Z, f"near AS (SELECT DISTINCT b.id FROM z a JOIN z b ON a.id < b.id AND round(list_dot_product(a.z, b.z), 9) >= {COPY})", select="SELECT id AS sample_id FROM z WHERE id NOT IN (SELECT id FROM near)"))
def _(spark, d):
    return drop_near_copies(e_all(spark, d), COPY).select("sample_id")


@R.add("bl_retrieval_cluster", P.with_(*E_ASSIGNED, P.assign("ra", "ref", "m_c"), "hit AS (SELECT k, count(*) AS n FROM ra GROUP BY k)", f"q AS (SELECT k, floor(round(CAST(({B30}) AS DOUBLE) * n / sum(n) OVER (), 9)) AS quota FROM hit)", select="SELECT id AS sample_id, k AS cluster_id, round(sim, 6) AS sim FROM (SELECT a.*, quota, row_number() OVER (PARTITION BY k ORDER BY round(sim, 9) DESC, id) AS rk FROM a JOIN q USING (k)) WHERE rk <= quota"))
def _(spark, d):
    return r6(B.retrieval_clusters(e_pool(spark, d), e_ref(spark, d), e_model(spark, d), _b30(spark, d)), "sim")


@R.add("bl_anchor_stratified", P.with_("docs AS (SELECT doc_id AS id, source, lang FROM documents)", sel_anchor("s", "docs", "source || '|' || lang", "SELECT count(*) * 3000 // 10000 FROM docs"), select="SELECT id AS sample_id, stratum FROM s"))
def _(spark, d):
    rows = table(spark, d, "documents").select(F.col("doc_id").alias("sample_id"), "source", "lang")
    return B.anchor_stratified(rows, [F.col("source"), F.col("lang")], rows.count() * 3000 // 10000)


@R.add("bl_rules", P.with_(P.DOC_H, "f AS (SELECT doc_id AS id, source FROM documents JOIN dh ON id = doc_id WHERE length(text) >= 300 AND h >= 2.6 AND doc_id IN (SELECT min(doc_id) FROM documents WHERE length(text) >= 300 GROUP BY text))", select=f"SELECT id AS sample_id, source FROM (SELECT *, row_number() OVER (PARTITION BY source ORDER BY {P.hash_order('id')}, id) AS rk FROM f) WHERE rk <= 15"))
def _(spark, d):
    samples = docs(spark, d).drop("stratum").join(table(spark, d, "documents").select(F.col("doc_id").alias("sample_id"), "source"), "sample_id")
    return B.rule_curation(samples, H.sample_entropy(docs(spark, d)), 300, 2.6, 15)


@R.add("bl_rules_classes_copies", P.with_(P.DOC_H, P.DOC_VEC, "cl AS (SELECT source FROM documents JOIN dh ON id = doc_id GROUP BY source HAVING round(avg(h), 9) >= 2.87)", "f AS MATERIALIZED (SELECT doc_id AS id, source FROM documents JOIN dh ON id = doc_id WHERE length(text) >= 300 AND h >= 2.6 AND source IN (SELECT source FROM cl) AND doc_id IN (SELECT min(doc_id) FROM documents WHERE length(text) >= 300 GROUP BY text))", "v AS MATERIALIZED (SELECT id, z FROM dz JOIN f USING (id))", "n AS (SELECT DISTINCT b.id FROM v a JOIN v b ON a.id < b.id AND round(list_dot_product(a.z, b.z), 9) >= 0.95)", select=f"SELECT id AS sample_id, source FROM (SELECT *, row_number() OVER (PARTITION BY source ORDER BY {P.hash_order('id')}, id) AS rk FROM f WHERE id NOT IN (SELECT id FROM n)) WHERE rk <= 15"))
def _(spark, d):
    """The rules, and besides no near copies and no sources of low mean entropy."""
    samples = docs(spark, d).drop("stratum").join(table(spark, d, "documents").select(F.col("doc_id").alias("sample_id"), "source"), "sample_id")
    return B.rule_curation(samples, H.sample_entropy(docs(spark, d)), 300, 2.6, 15, 2.87, features.hashed_tokens(docs(spark, d)).filter("vec IS NOT NULL"))


_SCORE = "(quality * 1000 + n_chars * 100 // (n_chars + 1000)) / 3000.0::DOUBLE"


@R.add("bl_score", f"SELECT d.doc_id AS sample_id, {_SCORE} AS score FROM documents d JOIN labels USING (doc_id) ORDER BY score DESC, {P.hash_order('d.doc_id')}, d.doc_id LIMIT 150")
def _(spark, d):
    """Scores below one and with ties: the label, and within a label the length in steps."""
    points = F.col("quality") * 1000 + F.floor(F.col("n_chars") * 100 / (F.col("n_chars") + 1000))
    scores = table(spark, d, "labels").join(table(spark, d, "documents").select("doc_id", "n_chars"), "doc_id").select(F.col("doc_id").alias("sample_id"), (points / F.lit(3000.0)).alias("score"))
    return B.score_ranked(docs(spark, d), scores, 150)


@R.add("bl_union_capped", f"SELECT bank, sample_id, class_label FROM (SELECT 'bank' || CAST(label // 2 + 1 AS VARCHAR) AS bank, vec_id AS sample_id, CAST(label AS VARCHAR) AS class_label, row_number() OVER (PARTITION BY label ORDER BY {P.hash_order('vec_id')}, vec_id) AS rk FROM embeddings WHERE vec_id % 5 < 2) WHERE rk <= 12")
def _(spark, d):
    sets = [C.reference_bank({f"bank{i}": bank(spark, d, labels)}).drop("vec") for i, labels in enumerate(BANK_LABELS, 1)]
    return B.union_capped(sets, 12)


@R.add("bl_centroids_full", P.with_(*BASE, P.kmeans("m", "pool", K_E, ITERS), select="SELECT k AS cluster_id, list_transform(z, lambda x: round(x, 6)) AS centroid FROM m_c"))
def _(spark, d):
    return B.centroids_full(e_pool(spark, d), K_E, ITERS).frame(spark).select("cluster_id", F.transform("centroid", lambda x: F.round(x, 6)).alias("centroid"))


@R.add("bl_centroids_entropy_pruned", P.with_(P.E, P.Z, P.POOL, P.E_H, P.top_h("th", "eh", "SELECT count(*) * 3000 // 10000 FROM eh"), "kept AS MATERIALIZED (SELECT * FROM pool WHERE id IN (SELECT id FROM th))", P.projected("pp", "kept", 64, 8), P.minibatch("m", "pp", 10, 10), select="SELECT k AS cluster_id, list_transform(z, lambda x: round(x, 6)) AS centroid FROM m_c"))
def _(spark, d):
    kept = H.prune_top_fraction(e_scores(spark, d), 3000).select("sample_id")
    model = B.centroids_minibatch(e_pool(spark, d).join(kept, "sample_id", "left_semi"), 10, 64, 8, 10)
    return model.frame(spark).select("cluster_id", F.transform("centroid", lambda x: F.round(x, 6)).alias("centroid"))


# Measures, on the 30 % of the candidates with the highest entropy against the held-out rows

MS = (*BASE, P.TEST, P.CAND, sel_entropy("se", "cand", "SELECT count(*) * 3000 // 10000 FROM cand"), "sel AS MATERIALIZED (SELECT cand.* FROM cand JOIN se USING (id))")


def selection(spark, d):
    cand = stage(spark, e_candidates(spark, d), "cand")
    scored = e_scores(spark, d).join(cand.select("sample_id"), "sample_id", "left_semi")
    return cand.join(H.prune_top_fraction(scored, 3000).select("sample_id"), "sample_id", "left_semi")


def moments6(df):
    return r6(df, "mean_part", "spread_part", "moment")


@R.add("ms_moment_diag", P.with_(*MS, select=P.moment("sel", "test")))
def _(spark, d):
    return moments6(M.moment_distance(selection(spark, d), e_test(spark, d)))


@R.add("ms_moment_full")
def _(spark, d):
    return spark.createDataFrame([(M.moment_distance_full(selection(spark, d), e_test(spark, d), 64),)], "moment double")


def pooled_sql(v: str, side: int, cell: int) -> str:
    out = side // cell
    return f"list_transform(range({out * out}), lambda c: list_sum(list_transform(range({cell * cell}), lambda i: {v}[1 + ((c // {out}) * {cell} + i // {cell}) * {side} + (c % {out}) * {cell} + i % {cell}])) / {cell * cell})"


def gap_sql(a: str, b: str) -> str:
    return f"(2 - 2 * list_dot_product({a}, {b}) / sqrt(list_dot_product({a}, {a}) * list_dot_product({b}, {b})))"


_PAIRS = (f"lo AS (SELECT id, v, {pooled_sql('v', 8, 2)} AS l FROM e)", "pr AS (SELECT id, v AS a, list_transform(range(64), lambda p: l[1 + (p // 8 // 2) * 4 + (p % 8) // 2]) AS b FROM lo)", f"pp AS (SELECT a, b, {pooled_sql('a', 8, 2)} AS a2, {pooled_sql('b', 8, 2)} AS b2, {pooled_sql('a', 8, 4)} AS a4, {pooled_sql('b', 8, 4)} AS b4 FROM pr)")


@R.add("ms_paired", P.with_(P.E, *_PAIRS, select=f"SELECT round(avg(({gap_sql('a', 'b')} + {gap_sql('a2', 'b2')} + {gap_sql('a4', 'b4')}) / 3), 6) AS paired FROM pp"))
def _(spark, d):
    low = e_all(spark, d).withColumn("low", M.pooled(F.col("vec"), 8, 2))
    return r6(M.paired_feature_distance(low.select(F.col("vec").alias("a"), M.expanded(F.col("low"), 8, 2).alias("b"))), "paired")


_SR = (f"sl AS (SELECT id, v, {pooled_sql('v', 8, 4)} AS l FROM sel)", f"tl AS (SELECT id, v, {pooled_sql('v', 8, 4)} AS l FROM test)", "nn AS (SELECT t.id AS tid, arg_min(s.v, {'s': -round(list_dot_product(t.l, s.l) / sqrt(list_dot_product(t.l, t.l) * list_dot_product(s.l, s.l)), 9), 'i': s.id}) AS guess, any_value(t.v) AS truth FROM tl t CROSS JOIN sl s GROUP BY t.id)")


@R.add("ms_sr", P.with_(*MS, *_SR, select="SELECT tid AS test_id, round(list_sum(list_transform(list_zip(truth, guess), lambda p: (p[1] - p[2]) * (p[1] - p[2]))), 6) AS gap FROM nn"))
def _(spark, d):
    return M.super_resolution(selection(spark, d), e_test(spark, d)).select("test_id", F.round(M.square_gap(F.col("truth"), F.col("guess")), 6).alias("gap"))


@R.add("ms_sis", P.with_(*MS, "cm AS (SELECT label, list(x ORDER BY pos) AS g FROM (SELECT label, pos, avg(x) AS x FROM (SELECT label, unnest(v) AS x, generate_subscripts(v, 1) AS pos FROM sel) GROUP BY ALL) GROUP BY label)", select="SELECT id AS test_id, round(list_sum(list_transform(list_zip(v, g), lambda p: (p[1] - p[2]) * (p[1] - p[2]))), 6) AS gap FROM test LEFT JOIN cm USING (label)"))
def _(spark, d):
    return M.from_condition(selection(spark, d), e_test(spark, d), "label").select("test_id", F.round(M.square_gap(F.col("truth"), F.col("guess")), 6).alias("gap"))


_BAL = "b AS (SELECT k, count(*) AS n, row_number() OVER (ORDER BY count(*), k) AS i FROM s GROUP BY k)"
_BAL_OUT = f"""SELECT count(*) AS groups, CAST(sum(n) AS BIGINT) AS rows, round((ln(sum(n)) - sum(n * ln(n)) / sum(n)) / ln({K_E}), 6) AS evenness,
round(CASE WHEN count(*) < {K_E} THEN 0.0 ELSE min(n) / sum(n) END, 6) AS min_share, round(max(n) / sum(n), 6) AS max_share,
round((2 * sum(i * n) + 2 * ({K_E} - count(*)) * sum(n)) / ({K_E} * sum(n)) - ({K_E} + 1) / {K_E}.0::DOUBLE, 6) AS gini FROM b"""


@R.add("ms_balance", P.with_(*E_ASSIGNED, P.scene("s", "a", HALF, K_E), _BAL, select=_BAL_OUT))
def _(spark, d):
    a = e_assigned(spark, d)
    return r6(M.balance(S.scene_sample(a, a.count() * 5000 // 10000, K_E), "cluster_id", K_E), "evenness", "min_share", "max_share", "gini")


@R.add("ms_representativeness", P.with_(*E_ASSIGNED, P.scene("s", "a", HALF, K_E), "pk AS (SELECT pool.* FROM pool JOIN s USING (id))", "nb AS (SELECT p.id, max(list_dot_product(p.z, k.z)) AS best FROM pool p CROSS JOIN pk k GROUP BY p.id)", select="SELECT round((SELECT avg(sim) FROM s), 6) AS to_centroid, round((SELECT avg(best) FROM nb), 6) AS pool_to_subset"))
def _(spark, d):
    a, pool = e_assigned(spark, d), e_pool(spark, d)
    s = stage(spark, S.scene_sample(a, a.count() * 5000 // 10000, K_E), "s")
    return r6(M.representativeness(s, pool, pool.join(s.select("sample_id"), "sample_id", "left_semi")), "to_centroid", "pool_to_subset")


@R.add("ms_redundancy", P.with_(P.E, P.Z, select="SELECT count(*) AS n, CAST(count(*) FILTER (near) AS BIGINT) AS with_neighbour, round(count(*) FILTER (near) / count(*), 6) AS share FROM (SELECT a.id, max(CASE WHEN a.id <> b.id THEN round(list_dot_product(a.z, b.z), 9) END) >= 0.45 AS near FROM z a CROSS JOIN z b GROUP BY a.id)"))
def _(spark, d):
    return r6(M.redundancy(e_all(spark, d), 0.45), "share")


@R.add("ms_entropy_profile", P.with_(P.DOC_H, P.top_h("t", "dh", "SELECT count(*) * 3000 // 10000 FROM dh"), select="SELECT CASE WHEN id IN (SELECT id FROM t) THEN 'kept' ELSE 'dropped' END AS part, count(*) AS n, round(avg(h), 6) AS mean_h, round(min(h), 6) AS min_h, round(median(round(h, 9)), 6) AS median_h, round(max(h), 6) AS max_h FROM dh GROUP BY 1"))
def _(spark, d):
    scored = stage(spark, H.sample_entropy(docs(spark, d)), "h")
    return r6(M.entropy_profile(scored, H.prune_top_fraction(scored, 3000)), "mean_h", "min_h", "median_h", "max_h")


@R.add("ms_purity", P.with_(*E_ASSIGNED, "g AS (SELECT k, label, count(*) AS n, sum(sim) AS s FROM a JOIN pool USING (id) GROUP BY ALL)", "t AS (SELECT k, max(n) AS top, sum(n) AS n, sum(s) AS s FROM g GROUP BY k)", select="SELECT CAST(sum(n) AS BIGINT) AS n, round(sum(top) / sum(n), 6) AS purity, round(sum(s) / sum(n), 6) AS mean_sim FROM t"))
def _(spark, d):
    return r6(M.purity(e_assigned(spark, d), e_pool(spark, d).select("sample_id", "label")), "purity", "mean_sim")


@R.add("ms_overlap", P.with_(*BASE, sel_random("x", "pool", B30), sel_entropy("y", "pool", B30), select="SELECT (SELECT count(*) FROM x) AS n_a, (SELECT count(*) FROM y) AS n_b, (SELECT count(*) FROM x JOIN y USING (id)) AS both, round((SELECT count(*) FROM x JOIN y USING (id)) / (SELECT count(*) FROM (SELECT id FROM x UNION SELECT id FROM y)), 6) AS jaccard"))
def _(spark, d):
    pool = e_pool(spark, d)
    scored = e_scores(spark, d).join(pool.select("sample_id"), "sample_id", "left_semi")
    return r6(M.overlap(B.random_rows(pool, _b30(spark, d)), H.prune_top_fraction(scored, 3000)), "jaccard")


def curves_sql(source: str, batch: int) -> str:
    """cv(method, step, n, moment) from source(method, id, v)."""
    return f"""cr AS (SELECT method, v, CAST((row_number() OVER (PARTITION BY method ORDER BY {P.hash_order('id')}, id) - 1) // {batch} + 1 AS BIGINT) AS step FROM {source}),
cs AS (SELECT method, step, pos, sum(x) AS s, sum(x * x) AS ss, count(*) AS c FROM (SELECT method, step, unnest(v) AS x, generate_subscripts(v, 1) AS pos FROM cr) GROUP BY ALL),
ca AS (SELECT method, step, pos, sum(s) OVER w AS s, sum(ss) OVER w AS ss, sum(c) OVER w AS n FROM cs WINDOW w AS (PARTITION BY method, pos ORDER BY step)),
ct AS (SELECT pos, avg(x) AS mu, stddev_pop(x) AS sd FROM (SELECT unnest(v) AS x, generate_subscripts(v, 1) AS pos FROM test) GROUP BY pos),
cv AS (SELECT method, step, CAST(max(n) AS BIGINT) AS n, sum(pow(s / n - mu, 2) + pow(sqrt(greatest(0.0, ss / n - (s / n) * (s / n))) - sd, 2)) AS moment FROM ca JOIN ct USING (pos) GROUP BY ALL)"""


_TWO = (*MS, sel_random("sr", "cand", "SELECT count(*) * 3000 // 10000 FROM cand"), "u AS (SELECT 'entropy' AS method, id, v FROM sel UNION ALL SELECT 'random', id, v FROM cand JOIN sr USING (id))", curves_sql("u", 8))


def _two(spark, d):
    cand = e_candidates(spark, d)
    chosen = B.random_rows(cand, cand.count() * 3000 // 10000)
    a = selection(spark, d).select(F.lit("entropy").alias("method"), "sample_id", "vec")
    return a.unionByName(cand.join(chosen, "sample_id", "left_semi").select(F.lit("random").alias("method"), "sample_id", "vec"))


@R.add("ms_convergence", P.with_(*_TWO, select="SELECT method, step, n, round(moment, 6) AS moment FROM cv"))
def _(spark, d):
    return r6(M.convergence(_two(spark, d), e_test(spark, d), 8), "moment")


@R.add("ms_steps_to_target", P.with_(*_TWO, select="SELECT method, min(step) FILTER (moment <= 0.1) AS steps FROM cv GROUP BY method"))
def _(spark, d):
    return M.steps_to_target(M.convergence(_two(spark, d), e_test(spark, d), 8), 0.1)


@R.add("ms_selection_stats", "SELECT count(*) AS n_total, CAST(floor(count(*) * 3000 // 10000) AS BIGINT) AS n, round(1 - (count(*) * 3000 // 10000) / count(*), 6) AS pruned FROM embeddings")
def _(spark, d):
    scored = e_scores(spark, d)
    return r6(M.selection_stats(scored.count(), H.prune_top_fraction(scored, 3000)), "pruned")


@R.add("ms_op_counts", f"SELECT * FROM (SELECT 'assignment' AS step, CAST(count(*) * {K_E} * 64 AS DOUBLE) AS ops FROM embeddings WHERE vec_id % 5 >= 2 UNION ALL SELECT 'centroids', CAST(count(*) * {ITERS * K_E * 64} AS DOUBLE) FROM embeddings WHERE vec_id % 5 < 2 UNION ALL SELECT 'entropy', CAST(count(*) * 64 AS DOUBLE) FROM embeddings WHERE vec_id % 5 >= 2 UNION ALL SELECT 'sampling', round(count(*) * log2(count(*) / {K_E}), 3) FROM embeddings WHERE vec_id % 5 >= 2)")
def _(spark, d):
    ops = M.op_counts(e_pool(spark, d).count(), K_E, 64, 64, ITERS, e_ref(spark, d).count())
    return spark.createDataFrame([(k, round(v, 3)) for k, v in ops.items()], "step string, ops double")
