"""The experiment workloads with their SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import assign as A
from ..operators import centroids as C
from ..operators import features
from ..operators import measures as M
from ..operators.entropy import prune_top_fraction, sample_entropy
from ..operators.sampling import hash_order
from ..plans import workloads as WL
from ..plans.pipeline import default_stage1_keep
from ..sources.tables import stage, table
from . import sqlparts as P
from .compare import MS, curves_sql, gap_sql, pooled_sql, sel_anchor, sel_cluster, sel_moderate, sel_random, sel_retrieval
from .core import r6
from .inputs import BANK_LABELS, ITERS, K_D, K_E, bank, curated_ids, d_ref, d_rows, docs, e_candidates, e_ref, e_scores, e_test, held_out
from .registry import Registry

R = Registry()
N = "SELECT count(*) FROM cand"
COUNTS = "SELECT {by}, CAST(sum(c) AS BIGINT) AS n, count(*) AS classes, round(CASE WHEN count(*) > 1 THEN (ln(sum(c)) - sum(c * ln(c)) / sum(c)) / ln(count(*)) ELSE 0.0 END, 6) AS evenness FROM (SELECT {by}, label, count(*) AS c FROM u GROUP BY ALL) GROUP BY {by}"
MEASURES = ("evenness", "moment")


def bench(spark, d) -> WL.Bench:
    return WL.Bench.build(e_candidates(spark, d), e_scores(spark, d), e_ref(spark, d), e_test(spark, d))


def bench_doc(spark, d) -> WL.Bench:
    """Documents: unlabelled ones are the pool, expert-curated ones the reference, languages the classes."""
    rows, scores = stage(spark, d_rows(spark, d), "rows"), stage(spark, sample_entropy(docs(spark, d)), "h")
    pool = rows.join(table(spark, d, "labels").select(F.col("doc_id").alias("sample_id")), "sample_id", "left_anti")
    test = stage(spark, held_out(pool, scores), "test")
    cand = pool.join(F.broadcast(test.select("sample_id")), "sample_id", "left_anti")  # 50 rows
    return WL.Bench.build(cand, scores, rows.join(curated_ids(spark, d), "sample_id", "left_semi"), test)


#: The same names as the tables of embeddings have, over documents.
D_MS = (
    P.DOC_VEC, P.DOC_H, "eh AS (SELECT id, h FROM dh)", "z AS MATERIALIZED (SELECT dz.id, lang AS label, dz.z AS v, dz.z FROM dz JOIN documents ON doc_id = dz.id)",
    "ref AS MATERIALIZED (SELECT * FROM z WHERE id IN (SELECT doc_id FROM labels WHERE quality = 1 AND toxic = 0))",
    "pool AS MATERIALIZED (SELECT * FROM z WHERE id NOT IN (SELECT doc_id FROM labels))", P.TEST, P.CAND,
)
#: suffix of the query, its bench, SQL tables and number of clusters
BENCHES = (("", bench, MS, K_E), ("_doc", bench_doc, D_MS, K_D))


def two_stage_cte(name: str, rho: int, keep: int, k: int, centroids: str, rows: str = "cand") -> str:
    n = f"SELECT count(*) FROM {rows}"
    top = P.top_h(f"{name}_h", f"(SELECT id, h, z FROM {rows} JOIN eh USING (id))", f"({n}) * {keep} // 10000")
    return ",\n".join([top, P.assign(f"{name}_a", f"{name}_h", centroids), P.scene(name, f"{name}_a", f"({n}) * {10000 - rho} // 10000", k)])


def union(parts: dict[str, str], by: str) -> str:
    """u(by columns, id, v, label) from {'value list': selection}."""
    names = by.split(", ")
    rows = [f"SELECT {', '.join(f'{v} AS {n}' for v, n in zip(values.split(', '), names, strict=True))}, id, v, label FROM cand WHERE id IN (SELECT id FROM {sel})" for values, sel in parts.items()]
    return "u AS MATERIALIZED (" + " UNION ALL ".join(rows) + ")"


def measured(by: str, more: str = "") -> str:
    return f"SELECT * FROM ({COUNTS.format(by=by)}) JOIN (SELECT {by}, moment FROM ({P.moment('u', 'test', 'v', by)})) USING ({by}){more}"


def _methods(rho: int, k: int, prefix: str = "", names: tuple[str, ...] = WL.METHODS, rows: str = "cand") -> tuple[list[str], dict[str, str]]:
    b, p = f"(SELECT count(*) FROM {rows}) * {10000 - rho} // 10000", prefix
    ctes = {
        "random": sel_random(f"{p}random", rows, b), "moderate": sel_moderate(f"{p}moderate", rows, b), "cluster_nearest": sel_cluster(f"{p}cluster_nearest", rows, b, k),
        "retrieval": sel_retrieval(f"{p}retrieval", rows, b), "anchor": sel_anchor(f"{p}anchor", rows, "label", b), "entropy": P.top_h(f"{p}entropy", f"(SELECT id, h FROM {rows} JOIN eh USING (id))", b),
        "two_stage": two_stage_cte(f"{p}two_stage", rho, default_stage1_keep(rho), k, "m_c", rows),
    }
    return [ctes[m] for m in names], {f"'{m}'": p + m for m in names}


KEEPS = [1000, 1500, 3000, 5000, 7000, 10000]
RHOS, ALL_RHOS = [5000, 7000, 9000], [0, 3000, 5000, 7000, 8500, 9000]
_GRID = {(r, p): f"g{r}_{p}" for r in (8500, 9000) for p in sorted({10000 - r, 3000, 5000, 7000})}
_FLOORS = "mh AS (" + " UNION ALL ".join(f"SELECT {k} AS keep_bp, round(min(h), 6) AS min_h FROM k{k}" for k in KEEPS) + ")"

for _suffix, _bench, _ms, _k in BENCHES:
    _model = P.kmeans("m", "ref", _k, ITERS)
    _c70, _u70 = _methods(7000, _k)
    _curves = {r: _methods(r, _k, f"c{r}_") for r in RHOS}

    @R.add(f"wl_stage1_sweep{_suffix}", P.with_(*_ms, *[P.top_h(f"k{k}", "(SELECT id, h FROM cand JOIN eh USING (id))", f"({N}) * {k} // 10000") for k in KEEPS], union({str(k): f"k{k}" for k in KEEPS}, "keep_bp"), _FLOORS, select=measured("keep_bp", " JOIN mh USING (keep_bp)")))
    def _(spark, d, build=_bench):
        return r6(WL.stage1_sweep(build(spark, d), KEEPS), *MEASURES, "min_h")

    @R.add(f"wl_compare_70{_suffix}", P.with_(*_ms, _model, *_c70, union(_u70, "method"), select=measured("method")))
    def _(spark, d, build=_bench, k=_k):
        return r6(WL.compare_methods(build(spark, d), 7000, k, ITERS), *MEASURES)

    @R.add(f"wl_curves{_suffix}", P.with_(*_ms, _model, *[c for ctes, _ in _curves.values() for c in ctes], union({f"'{r}:{m}'": f"c{r}_{m}" for r in RHOS for m in WL.METHODS}, "method"), curves_sql("u", 16), select="SELECT method, step, n, round(moment, 6) AS moment FROM cv"))
    def _(spark, d, build=_bench, k=_k):
        return r6(WL.convergence_curves(build(spark, d), RHOS, k, ITERS, 16, WL.METHODS), "moment")

    @R.add(f"wl_stage_grid{_suffix}", P.with_(*_ms, _model, *[two_stage_cte(n, r, p, _k, "m_c") for (r, p), n in _GRID.items()], union({f"{r}, {p}": n for (r, p), n in _GRID.items()}, "rho_bp, p1_bp"), select=measured("rho_bp, p1_bp")))
    def _(spark, d, build=_bench, k=_k):
        return r6(WL.stage_grid(build(spark, d), [8500, 9000], [3000, 5000, 7000], k, ITERS), *MEASURES)

    @R.add(f"wl_ratio_sweep{_suffix}", P.with_(*_ms, _model, *[two_stage_cte(f"s{r}", r, default_stage1_keep(r), _k, "m_c") for r in ALL_RHOS], union({str(r): f"s{r}" for r in ALL_RHOS}, "rho_bp"), select=measured("rho_bp")))
    def _(spark, d, build=_bench, k=_k):
        return r6(WL.ratio_sweep(build(spark, d), ALL_RHOS, k, ITERS), *MEASURES)


REF_MODEL = P.kmeans("m", "ref", K_E, ITERS)
_C70, _U70 = _methods(7000, K_E)


@R.add("ms_improvement", P.with_(*MS, REF_MODEL, *_C70, union(_U70, "method"), f"r AS ({measured('method')})", "p AS (SELECT min(moment) FILTER (method = 'two_stage') AS best, min(moment) FILTER (method <> 'two_stage') AS next_best FROM r)", select="SELECT best, next_best, round((next_best - best) / next_best, 6) AS improvement FROM p"))
def _(spark, d):
    results = stage(spark, r6(WL.compare_methods(bench(spark, d), 7000, K_E, ITERS), "moment"), "results")
    return r6(M.improvement(results, "moment", "two_stage"), "improvement")


SCALES = {"quarter": 4, "half": 2, "whole": 1}  # shares of the candidates, nested by hash: pools of several sizes
_SCALE_METHODS = ("random", "entropy", "two_stage")
_SCALED = {n: _methods(7000, K_E, f"{n}_", _SCALE_METHODS, f"cand_{n}") for n in SCALES}


@R.add("wl_scale_transfer", P.with_(*MS, REF_MODEL, *[f"cand_{n} AS MATERIALIZED (SELECT * FROM cand WHERE {P.hash_order('id')} < {2**52 // share})" for n, share in SCALES.items()], *[c for ctes, _ in _SCALED.values() for c in ctes], union({f"'{n}', {m}": sel for n, (_, names) in _SCALED.items() for m, sel in names.items()}, "scale, method"), select=measured("scale, method")))
def _(spark, d):
    b = bench(spark, d)
    sizes = {n: WL.Bench.build(b.cand.filter(hash_order() < 2**52 // share), b.scores, b.ref, b.test) for n, share in SCALES.items()}
    return r6(WL.scale_transfer(sizes, 7000, K_E, ITERS, _SCALE_METHODS), *MEASURES)


K_S = 10
_SOURCES = {"full": "cand", "narrow": "(SELECT * FROM ref WHERE label < 2)", "broad": "(SELECT * FROM ref WHERE id % 10 < 2)", "three": "(SELECT * FROM ref WHERE label < 6)", "five": "ref"}


def _source_ctes(names) -> list[str]:
    out = []
    for n in names:
        out += [f"src_{n} AS MATERIALIZED (SELECT * FROM {_SOURCES[n]})", P.kmeans(f"m_{n}", f"src_{n}", K_S, ITERS), two_stage_cte(f"s_{n}", 7000, default_stage1_keep(7000), K_S, f"m_{n}_c")]
    return out


def _sources(spark, d, b, names):
    ref = e_ref(spark, d)
    every = {"full": b.cand, "narrow": ref.filter("label < 2"), "broad": ref.filter("sample_id % 10 < 2"), "three": ref.filter("label < 6"), "five": ref}
    return {n: every[n] for n in names}


_FACTS = "f AS (" + " UNION ALL ".join(f"SELECT '{n}' AS source, count(*) AS rows, count(*) * {K_S * 64 * ITERS} AS products FROM src_{n}" for n in _SOURCES) + ")"
_PRUNED = (
    P.top_h("src_h", "(SELECT id, h FROM cand JOIN eh USING (id))", f"({N}) * 3000 // 10000"), "src_p AS MATERIALIZED (SELECT * FROM cand WHERE id IN (SELECT id FROM src_h))",
    P.projected("src_pruned_reduced", "src_p", 64, 8), P.minibatch("m_pr", "src_pruned_reduced", K_S, 10), P.projected("cand_8", "cand", 64, 8),
    two_stage_cte("s_pruned_reduced", 7000, default_stage1_keep(7000), K_S, "m_pr_c", "cand_8"),
)
_SIX = _FACTS[:-1] + f" UNION ALL SELECT 'pruned_reduced', count(*), count(*) * {K_S * 8} FROM src_pruned_reduced)"


def _six(spark, d, b):
    """The five sets of full dimensions, and the entropy-pruned pool in eight dimensions by ten mini-batches of a tenth: one pass."""
    pruned = b.cand.join(prune_top_fraction(b.scores, 3000, b.n).select("sample_id"), "sample_id", "left_semi")
    reduced = WL.Source(pruned, lambda rows: C.fit_minibatch(rows, K_S, 10), lambda rows: features.random_projection(rows, 64, 8), 1)
    return {**_sources(spark, d, b, _SOURCES), "pruned_reduced": reduced}


@R.add("wl_cluster_sources", P.with_(*MS, *_source_ctes(_SOURCES), *_PRUNED, union({f"'{n}'": f"s_{n}" for n in [*_SOURCES, "pruned_reduced"]}, "source"), _SIX, select=measured("source", " JOIN f USING (source)")))
def _(spark, d):
    b = bench(spark, d)
    return r6(WL.cluster_sources(b, _six(spark, d, b), K_S, ITERS), *MEASURES)


@R.add("wl_cluster_sources_timed")
def _(spark, d):
    b = bench(spark, d)
    return WL.cluster_sources(b, _six(spark, d, b), K_S, ITERS, timed=True)


KS = [5, 10, 20, 40]


@R.add("wl_k_sweep", P.with_(*MS, *[x for k in KS for x in (P.kmeans(f"m{k}", "ref", k, ITERS), P.assign(f"a{k}", "cand", f"m{k}_c"), P.scene(f"s{k}", f"a{k}", f"({N}) * 5000 // 10000", k))], union({str(k): f"s{k}" for k in KS}, "k"), "f AS (" + " UNION ALL ".join(f"SELECT {k} AS k, CAST(count(*) FILTER (n = 0) AS BIGINT) AS empty, CAST(count(*) FILTER (n < ({N}) * 5000 // 10000 // {k}) AS BIGINT) AS rare, (SELECT count(*) FROM s{k} WHERE picked_by = 'refill') AS refill FROM (SELECT c.k, count(a.id) AS n FROM m{k}_c c LEFT JOIN a{k} a ON a.k = c.k GROUP BY c.k)" for k in KS) + ")", select=measured("k", " JOIN f USING (k)")))
def _(spark, d):
    return r6(WL.k_sweep(bench(spark, d), KS, ITERS), *MEASURES)


_BANKS = {"narrow": 1, "three": 3, "five": 5}


@R.add("wl_bank_diversity", P.with_(*MS, *_source_ctes(_BANKS), union({f"'{n}'": f"s_{n}" for n in _BANKS}, "source"), _FACTS.split(" UNION ALL ")[0].split(" AS (")[0] + " AS (" + " UNION ALL ".join(f"SELECT '{n}' AS source, count(*) AS rows, count(*) * {K_S * 64 * ITERS} AS products FROM src_{n}" for n in _BANKS) + ")", select=measured("source", " JOIN f USING (source)")))
def _(spark, d):
    banks = {f"bank{i}": bank(spark, d, labels) for i, labels in enumerate(BANK_LABELS, 1)}
    chosen = {n: C.reference_bank(banks, [f"bank{i}" for i in range(1, c + 1)]) for n, c in _BANKS.items()}
    return r6(WL.cluster_sources(bench(spark, d), chosen, K_S, ITERS), *MEASURES)


@R.add("wl_class_vs_over", P.with_(*MS, REF_MODEL, "cs AS (SELECT label, list(s ORDER BY pos) AS v FROM (SELECT label, pos, sum(x) AS s FROM (SELECT label, unnest(z) AS x, generate_subscripts(z, 1) AS pos FROM ref) GROUP BY ALL) GROUP BY label)", f"cc AS (SELECT CAST(row_number() OVER (ORDER BY label) - 1 AS INTEGER) AS k, {P.unit('v')} AS z FROM cs)", P.assign("a1", "cand", "cc"), P.assign("a2", "cand", "m_c"), select=f"SELECT 'class' AS kind, CAST((SELECT count(*) FROM cc) AS INTEGER) AS k, round(avg(sim), 6) AS cohesion FROM a1 UNION ALL SELECT 'overcluster', {K_E}, round(avg(sim), 6) FROM a2"))
def _(spark, d):
    return r6(WL.class_vs_overcluster(bench(spark, d), K_E, ITERS), "cohesion")


def _pairs(sel: str) -> dict[str, str]:
    """(a, b) of truth and guess for both downstream proxies of a selection."""
    near = "arg_min(s.v, {'s': -round(list_dot_product(t.l, s.l) / sqrt(list_dot_product(t.l, t.l) * list_dot_product(s.l, s.l)), 9), 'i': s.id})"
    sr = f"SELECT any_value(t.v) AS a, {near} AS b FROM tl t CROSS JOIN (SELECT * FROM cl WHERE id IN (SELECT id FROM {sel})) s GROUP BY t.id"
    mean = f"SELECT label, list(x ORDER BY pos) AS g FROM (SELECT label, pos, avg(x) AS x FROM (SELECT label, unnest(v) AS x, generate_subscripts(v, 1) AS pos FROM cand WHERE id IN (SELECT id FROM {sel})) GROUP BY ALL) GROUP BY label"
    return {"sr": sr, "sis": f"SELECT v AS a, g AS b FROM test LEFT JOIN ({mean}) USING (label)"}


def _scores_of(method: str, sel: str) -> str:
    cols = [f"{method} AS method", f"(SELECT moment FROM ({P.moment('(SELECT v FROM cand WHERE id IN (SELECT id FROM ' + sel + '))', 'test')})) AS moment"]
    levels = ", ".join(f"{pooled_sql(x, 8, c)} AS {x}{c}" for x in "ab" for c in (2, 4))
    for name, pairs in _pairs(sel).items():
        cols.append(f"(SELECT round(avg(list_sum(list_transform(list_zip(a, b), lambda p: (p[1] - p[2]) * (p[1] - p[2])))), 6) FROM ({pairs}) WHERE b IS NOT NULL) AS {name}")
        cols.append(f"(SELECT round(avg(({gap_sql('a', 'b')} + {gap_sql('a2', 'b2')} + {gap_sql('a4', 'b4')}) / 3), 6) FROM (SELECT a, b, {levels} FROM ({pairs}) WHERE b IS NOT NULL)) AS {name}_paired")
    cols.append(f"(SELECT round(avg(CASE WHEN b IS NULL THEN 1.0 ELSE 0.0 END), 6) FROM ({_pairs(sel)['sis']})) AS unsupported")
    return "SELECT " + ", ".join(cols)


_REST = (f"tl AS MATERIALIZED (SELECT id, v, {pooled_sql('v', 8, 4)} AS l FROM test)", f"cl AS MATERIALIZED (SELECT id, v, {pooled_sql('v', 8, 4)} AS l FROM cand)")
_SCORES = "sc AS MATERIALIZED (" + " UNION ALL ".join(_scores_of(m, s) for m, s in _U70.items()) + ")"
_DOWN = ("moment", "sr", "sr_paired", "sis", "sis_paired", "unsupported")


@R.add("wl_downstream", P.with_(*MS, REF_MODEL, *_C70, *_REST, _SCORES, select="SELECT * FROM sc"))
def _(spark, d):
    return r6(WL.restoration_scores(bench(spark, d), 7000, K_E, ITERS), *_DOWN)


@R.add("wl_metric_agreement", P.with_(*MS, REF_MODEL, *_C70, *_REST, _SCORES, select=" UNION ALL ".join(f"SELECT '{m}' AS measure, count(*) AS n, round(corr(x, y), 6) AS spearman FROM (SELECT CAST(rank() OVER (ORDER BY moment) AS DOUBLE) AS x, CAST(rank() OVER (ORDER BY {m}) AS DOUBLE) AS y FROM sc)" for m in ("sr", "sr_paired", "sis", "sis_paired"))))
def _(spark, d):
    scores = r6(WL.restoration_scores(bench(spark, d), 7000, K_E, ITERS), *_DOWN)
    return r6(WL.metric_agreement(stage(spark, scores, "scores"), "moment", ["sr", "sr_paired", "sis", "sis_paired"]), "spearman")


@R.add("wl_holdout", P.with_(P.E, P.Z, P.POOL, P.E_H, P.TEST, select="SELECT id AS sample_id FROM test"))
def _(spark, d):
    return e_test(spark, d).select("sample_id")


@R.add("wl_web_filter", P.with_("w AS (SELECT page_id, trim(regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '[ \\n\\r\\t]+', ' ', 'g')) AS t FROM pages)", "f AS (SELECT page_id AS pid, t FROM w WHERE length(t) >= 1200)", P.byte_h("fh", "f", "pid", "t"), select="SELECT min(id) AS sample_id, any_value(length(t)) AS n_chars, round(any_value(h), 6) AS entropy FROM fh JOIN f ON pid = id WHERE h >= 2.9 GROUP BY t"))
def _(spark, d):
    return r6(WL.web_filter(table(spark, d, "pages"), 1200, 2.9), "entropy")


_PART = (
    "pc AS (SELECT l_partkey AS id, CAST(l_quantity AS INTEGER) AS q, CAST(count(*) AS DOUBLE) AS n FROM lineitem GROUP BY ALL)",
    "pf AS (SELECT i.id, b.q, coalesce(pc.n, 0.0) AS n FROM (SELECT DISTINCT id FROM pc) i CROSS JOIN (SELECT unnest(range(1, 51)) AS q) b LEFT JOIN pc ON pc.id = i.id AND pc.q = b.q)",
    "pv AS (SELECT id, list(n ORDER BY q) AS v, greatest(0.0, ln(sum(n)) - sum(CASE WHEN n > 0 THEN n * ln(n) ELSE 0 END) / sum(n)) AS h FROM pf GROUP BY id)",
    f"pz AS MATERIALIZED (SELECT id, v, h, {P.unit('v')} AS z FROM pv)",
    "pr AS MATERIALIZED (SELECT * FROM pz WHERE id % 5 = 0)",
    P.kmeans("m", "pr", 8, ITERS),
    P.assign("a", "(SELECT * FROM pz WHERE id % 5 <> 0)", "m_c"),
)


@R.add("wl_part_profile", P.with_(*_PART, select="SELECT a.id AS sample_id, p_type AS label, round(h, 6) AS entropy, a.k AS cluster_id, round(sim, 6) AS sim FROM a JOIN pz USING (id) JOIN part ON p_partkey = a.id"))
def _(spark, d):
    rows = stage(spark, WL.part_profiles(table(spark, d, "part"), table(spark, d, "lineitem")), "profiles")
    model = C.fit_centroids(rows.filter("sample_id % 5 = 0"), 8, ITERS)
    pool = rows.filter("sample_id % 5 <> 0")
    return r6(A.assign_clusters(pool, model).join(pool.drop("vec"), "sample_id"), "entropy", "sim").select("sample_id", "label", "entropy", "cluster_id", "sim")


@R.add("wl_population_slices", P.with_(P.DOC_H, P.top_h("t", "dh", "SELECT count(*) * 3000 // 10000 FROM dh"), select="SELECT lang AS stratum, count(*) AS n, count(t.id) AS kept, round(avg(dh.h), 6) AS mean_h FROM dh JOIN documents ON doc_id = dh.id LEFT JOIN t ON t.id = dh.id GROUP BY 1"))
def _(spark, d):
    scored = stage(spark, sample_entropy(docs(spark, d)), "h")
    return r6(WL.population_slices(scored, docs(spark, d), 3000), "mean_h")


_OFF = "SELECT '{name}' AS bank, round(avg(sim), 6) AS cohesion FROM a_{name}"


@R.add("wl_off_domain_bank", P.with_(P.DOC_VEC, P.text_vec("b", "benchmark", "item_id", "text"), P.D_REF, P.kmeans("mb", "bz", 8, ITERS), P.kmeans("mc", "dref", 8, ITERS), P.assign("a_benchmark", "dz", "mb_c"), P.assign("a_curated", "dz", "mc_c"), select=_OFF.format(name="benchmark") + " UNION ALL " + _OFF.format(name="curated")))
def _(spark, d):
    """Documents assigned to centroids of the benchmark texts (off-domain bank) and of curated documents: cohesion of both."""
    items = table(spark, d, "benchmark").select(F.col("item_id").alias("sample_id"), F.col("text").alias("payload"))
    pool, out = features.hashed_tokens(docs(spark, d)), []
    for name, ref in (("benchmark", features.hashed_tokens(items)), ("curated", d_ref(spark, d))):
        m = C.fit_centroids(ref.filter("vec IS NOT NULL"), 8, ITERS)
        out.append(A.assign_clusters(pool, m).agg(F.lit(name).alias("bank"), F.round(F.avg("sim"), 6).alias("cohesion")))
    return out[0].unionByName(out[1])
