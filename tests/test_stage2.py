import numpy as np
import pytest
from hypothesis import HealthCheck, given, settings
from hypothesis import strategies as st

from subsetlab.operators import assign as A
from subsetlab.operators import centroids as C
from subsetlab.operators import measures as M
from subsetlab.operators import sampling as S
from subsetlab.operators.select import SelectionPlanner, flag_top_q, group_median, rank_in_group, top_n, top_q_per_group
from subsetlab.plans.pipeline import budget_of, default_stage1_keep
from subsetlab.sources.tables import stage

FORCE = SelectionPlanner(sort_rows=0, window_rows=0, boundary_rows=3)
POOL = [(1, 0, 0.99), (2, 0, 0.95), (3, 0, 0.90), (4, 0, 0.70), (5, 1, 0.60)]


@pytest.mark.parametrize(("budget", "quota", "fill"), [(1, "", "a"), (2, "ae", ""), (3, "ae", "b"), (4, "abe", "c"), (5, "abe", "cd"), (6, "abce", "d"), (0, "", ""), (50, "abcde", "")])
def test_worked_example(spark, budget, quota, fill):
    df = spark.createDataFrame(POOL, "sample_id long, cluster_id int, sim double")
    for planner in (SelectionPlanner(), FORCE):
        rows = S.scene_sample(df, budget, 2, planner=planner).collect()
        assert {r.picked_by: "".join(sorted("?abcde"[x.sample_id] for x in rows if x.picked_by == r.picked_by)) for r in rows} == {k: v for k, v in (("quota", quota), ("refill", fill)) if v}
    single = S.scene_sample_single_plan(df, budget, 2).collect()
    assert {(r.sample_id, r.picked_by, r.rank_in_cluster) for r in single} == {(r.sample_id, r.picked_by, r.rank_in_cluster) for r in rows}


def model(*rows):
    return C.CentroidModel(np.array(rows, float))


@pytest.mark.parametrize("engine", ["arrow", "sql"])
def test_assignment(spark, engine):
    df = spark.createDataFrame([(1, [3.0, 4.0]), (2, [30.0, 40.0]), (3, [1.0, 1.0]), (4, [0.0, 0.0]), (5, None), (6, [float("nan"), 1.0])], "sample_id long, vec array<double>")
    got = {r.sample_id: (r.cluster_id, r.sim and round(r.sim, 6)) for r in A.assign_clusters(df, model([1, 0], [0, 1]), engine=engine).collect()}
    assert got == {1: (1, 0.8), 2: (1, 0.8), 3: (0, 0.707107), 4: (None, None), 5: (None, None), 6: (None, None)}
    inner = {r.sample_id: (r.cluster_id, r.sim) for r in A.assign_clusters(df, model([1, 0], [0, 1]), "inner", engine).collect()}
    assert inner[1] == (1, 4.0) and inner[2] == (1, 40.0)


def test_wrong_length_raises(spark):
    df = spark.createDataFrame([(1, [1.0, 2.0, 3.0])], "sample_id long, vec array<double>")
    with pytest.raises(Exception, match="length 2"):
        A.assign_clusters(df, model([1, 0], [0, 1])).collect()


def test_kmeans_against_numpy(spark, sf):
    from subsetlab.catalog.inputs import e_ref

    ref = e_ref(spark, sf).orderBy("sample_id").collect()
    z = np.array([r.vec for r in ref])
    z /= np.linalg.norm(z, axis=1, keepdims=True)
    c = z[:12].copy()
    gains = []
    for _ in range(4):
        sim = np.round(z @ c.T, 9)
        at = sim.argmax(1)
        gains.append(sim.max(1).mean())
        for k in range(12):
            if (at == k).any():
                c[k] = z[at == k].sum(0)
        c /= np.linalg.norm(c, axis=1, keepdims=True)
    for parts, local in ((1, 0), (7, 0), (3, 10**6)):
        fitted = C.fit_centroids(e_ref(spark, sf).repartition(parts), 12, 4, local_numbers=local)
        assert np.abs(fitted.matrix - c).max() < 1e-9
        assert np.allclose(fitted.history, gains) and all(b >= a - 1e-9 for a, b in zip(gains, gains[1:], strict=False))
    with pytest.raises(ValueError, match="clusters need"):
        C.fit_centroids(e_ref(spark, sf).limit(3), 12)


def test_costs_of_clustering(spark, sf):
    from subsetlab.catalog.inputs import e_ref

    cost = {}
    for local in (0, 10**6):
        with M.CostReport(spark) as c:
            C.fit_centroids(e_ref(spark, sf).repartition(4), 12, 2, local_numbers=local)
        cost[local] = c
    assert cost[0].shuffle_bytes > cost[10**6].shuffle_bytes >= 0 and all(c.seconds > 0 for c in cost.values())


def test_model_round_trip(spark, tmp_path):
    m = model([1, 0], [0, 1])
    m.save(spark, str(tmp_path / "m"))
    assert (C.CentroidModel.load(spark, str(tmp_path / "m")).matrix == m.matrix).all()


@settings(max_examples=8, deadline=None, suppress_health_check=[HealthCheck.function_scoped_fixture])
@given(st.lists(st.tuples(st.integers(0, 3), st.integers(0, 6)), min_size=1, max_size=60), st.integers(0, 70))
def test_kernels_against_sorting(spark, rows, n):
    df = spark.createDataFrame([(i, g, s / 3) for i, (g, s) in enumerate(rows)], "id long, g int, s double")
    order = sorted(((-s / 3, i, g) for i, (g, s) in enumerate(rows)))
    assert {r.id for r in top_n(df, n, "s", "id", FORCE).collect()} == {i for _, i, _ in order[:n]}
    want = {i for k in range(4) for _, i, _ in [x for x in order if x[2] == k][:n]}
    assert {r.id for r in top_q_per_group(df, "g", n, "s", "id", FORCE).collect()} == want


@settings(max_examples=4, deadline=None, suppress_health_check=[HealthCheck.function_scoped_fixture])
@given(st.lists(st.tuples(st.integers(0, 3), st.integers(0, 5)), min_size=1, max_size=50), st.lists(st.integers(0, 20), min_size=4, max_size=4))
def test_group_kernels_against_sorting(spark, rows, quotas):
    df = stage(spark, spark.createDataFrame([(i, g, s / 3) for i, (g, s) in enumerate(rows)], "id long, g int, s double"), "t")
    order = {g: sorted((-s / 3, i) for i, (h, s) in enumerate(rows) if h == g) for g in range(4)}
    quota = spark.createDataFrame(list(enumerate(quotas)), "g int, quota long")
    want = {i for g in range(4) for _, i in order[g][: quotas[g]]}
    for planner in (SelectionPlanner(), FORCE):
        assert {r.id for r in flag_top_q(df, "g", quota, "s", "id", planner).collect() if r.picked} == want
        assert {r.id: r.rank for r in rank_in_group(df, "g", "s", "id", "rank", planner).collect()} == {i: k for g in order.values() for k, (_, i) in enumerate(g, 1)}
        got = {r.g: (r.median, r.n) for r in group_median(df, "g", "s", "id", planner).collect()}
        assert {g: (pytest.approx(np.median([-s for s, _ in v])), len(v)) for g, v in order.items() if v} == got


def test_plans_of_group_kernels(spark, sf):
    """Few winners: groups are limited early. Flags: no window over whole groups. Selected vectors meet narrow rows only."""
    rows = stage(spark, spark.range(5000).selectExpr("id AS sample_id", "CAST(id % 7 AS INT) AS cluster_id", "id / 7.0 AS sim"), "t")
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    assert "WindowGroupLimit" in plan(top_q_per_group(rows, "cluster_id", 20, "sim", "sample_id"))
    for planner in (SelectionPlanner(), FORCE):
        flagged = plan(flag_top_q(rows, "cluster_id", 20, "sim", "sample_id", planner))
        assert "Window" not in flagged and "Exchange hashpartitioning" not in flagged and "BroadcastHashJoin" in flagged
    dealt = rank_in_group(rows, "cluster_id", "sim", "sample_id", "r", SelectionPlanner(sort_rows=10))
    assert "hashpartitioning(cluster_id" in plan(dealt) and "_p" in plan(dealt).split("hashpartitioning(cluster_id")[1][:20]


def test_selection_invariants(spark, sf):
    from subsetlab.catalog.inputs import e_pool, e_ref

    fitted = C.fit_centroids(e_ref(spark, sf), 20, 3)
    assigned = A.assign_clusters(e_pool(spark, sf), fitted).collect()
    df = spark.createDataFrame(assigned, "sample_id long, cluster_id int, sim double")
    sizes = {r.cluster_id: r.n for r in A.pool_sizes(df, 20).collect()}
    assert sum(sizes.values()) == len(assigned)
    for budget in (30, 31, 150, 299):
        rows = S.scene_sample(df, budget, 20).collect()
        assert len(rows) == budget == len({r.sample_id for r in rows})
        for k, n in sizes.items():
            assert sum(r.cluster_id == k for r in rows) >= min(budget // 20, n)
        left = max((round(a.sim, 9) for a in assigned if a.sample_id not in {r.sample_id for r in rows}), default=-1)
        assert all(round(r.sim, 9) >= left for r in rows if r.picked_by == "refill")
    assert {r.sample_id for r in S.scene_sample(df, 40, 20).collect()} <= {r.sample_id for r in S.scene_sample(df, 41, 20).collect()}


def test_moment_distance(spark):
    rows = lambda *v: spark.createDataFrame([(i, [float(x) for x in r]) for i, r in enumerate(v)], "sample_id long, vec array<double>")
    r = M.moment_distance(rows((1, 0), (0, 1)), rows((1, 0), (1, 0))).first()
    assert (round(r.mean_part, 9), round(r.spread_part, 9), round(r.moment, 9)) == (0.5, 0.5, 1.0)
    same = rows((1, 0), (0, 1), (2, 3))
    assert M.moment_distance_full(same, same, 2) == pytest.approx(0, abs=1e-6)


def test_prune_assigns_before_it_joins_many_survivors(spark, monkeypatch):
    from subsetlab.plans import pipeline

    rng = np.random.default_rng(11)
    vectors = stage(spark, spark.createDataFrame([(i, rng.normal(size=4).tolist()) for i in range(60)], "sample_id long, vec array<double>"), "v")
    scored = spark.createDataFrame([(i, float(x)) for i, x in enumerate(rng.random(60))], "sample_id long, entropy double")
    m = model([1, 0, 0, 0], [0, 1, 0, 0], [0, 0, 1, 0])
    few = {tuple(r) for r in pipeline.prune(scored, vectors, m, 8500).selected.collect()}
    joined = []
    monkeypatch.setattr(pipeline, "BROADCAST_IDS", 0)
    monkeypatch.setattr(pipeline, "stage", lambda s, df, name: joined.append((name, df._jdf.queryExecution().analyzed().toString())) or stage(s, df, name))
    many = {tuple(r) for r in pipeline.prune(scored, vectors, m, 8500).selected.collect()}
    assert few == many and len(few) == 9
    plan = dict(joined)["assigned"]
    assert plan.index("Join LeftSemi") < plan.index("MapInArrow")  # the join stands above the map


def test_budgets():
    assert [budget_of(1001, r) for r in (0, 7000, 8500, 10_000)] == [1001, 300, 150, 0]
    assert [default_stage1_keep(r) for r in (9000, 8500, 7000, 5000, 0)] == [3000, 3000, 6000, 10_000, 10_000]
    assert M.op_counts(1000, 20, 64, 64, 5, 200)["assignment"] == 1000 * 20 * 64
