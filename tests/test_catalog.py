import math
import re
from concurrent.futures import ThreadPoolExecutor

import duckdb
import pytest

import __spark_entry__ as entry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
WHERE = "/root/testdata/sf0.01"
#: Those of the llm subpackage are tested beside it.
CHECKED = [n for n in entry.oracle_sql() if not re.match(r"op\d", n)]


def plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else v
    if isinstance(v, (list, tuple)):
        return tuple(map(plain, v))
    return v.isoformat() if hasattr(v, "isoformat") else v


def both_sides(spark, name):
    """Columns and sorted rows of the query and of its SQL."""
    df = entry.queries()[name](spark, WHERE)
    cols = sorted(df.columns)
    got = [tuple(plain(r[c]) for c in cols) for r in df.collect()]
    con = duckdb.connect()
    con.execute("SET threads = 2")
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{WHERE}/{t}.parquet'")
    cursor = con.execute(entry.oracle_sql()[name])
    names = [c[0] for c in cursor.description]
    want = [tuple(plain(r[names.index(c)]) for c in cols) for r in cursor.fetchall()] if sorted(names) == cols else None
    return cols, sorted(names), got, want


@pytest.fixture(scope="module")
def answers(spark):
    """All queries, four at a time: most of each is the fixed cost of small jobs."""
    pool = ThreadPoolExecutor(4)
    yield {n: pool.submit(both_sides, spark, n) for n in CHECKED}
    pool.shutdown(cancel_futures=True)


def near(a, b):
    if isinstance(a, float) and isinstance(b, float):
        return a == pytest.approx(b, abs=2e-6, rel=2e-6)
    return len(a) == len(b) and all(map(near, a, b)) if isinstance(a, tuple) and isinstance(b, tuple) else a == b


@pytest.mark.parametrize("name", CHECKED)
def test_query_equals_sql(answers, name):
    cols, names, got, want = answers[name].result()
    assert names == cols and len(got) == len(want)
    order = lambda r: repr(tuple(round(x, 4) if isinstance(x, float) else x for x in r))
    assert all(near(a, b) for a, b in zip(sorted(got, key=order), sorted(want, key=order), strict=True))


def test_curves_and_sources_are_complete(answers):
    from subsetlab.plans.workloads import METHODS

    for name in ("wl_curves", "wl_curves_doc"):
        cols, _, got, _ = answers[name].result()
        assert {r[cols.index("method")] for r in got} == {f"{r}:{m}" for r in (5000, 7000, 9000) for m in METHODS}
    cols, _, got, _ = answers["wl_cluster_sources"].result()
    rows = {r[cols.index("source")]: dict(zip(cols, r, strict=True)) for r in got}
    assert rows.keys() == {"full", "narrow", "broad", "three", "five", "pruned_reduced"} and len({r["n"] for r in rows.values()}) == 1
    assert 0 < rows["pruned_reduced"]["rows"] < rows["full"]["rows"] and rows["pruned_reduced"]["products"] == rows["pruned_reduced"]["rows"] * 10 * 8


def test_timed_sources(spark, sf):
    rows = entry.queries()["wl_cluster_sources_timed"](spark, sf).collect()
    assert len(rows) == 6 and all(r.seconds > 0 for r in rows)


def test_every_sql_has_a_query_and_entry_runs(spark):
    assert entry.oracle_sql().keys() <= entry.queries().keys()
    assert entry.entry(spark).count() > 0


def test_plans(spark, sf):
    from subsetlab.catalog.inputs import e_pool
    from subsetlab.operators.assign import assign_clusters
    from subsetlab.operators.centroids import CentroidModel
    from subsetlab.operators.entropy import sample_entropy
    from subsetlab.catalog.inputs import docs
    import numpy as np

    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    h = plan(sample_entropy(docs(spark, sf)))
    assert "Exchange" not in h and "ReadSchema: struct<doc_id:bigint,text:string>" in h
    a = plan(assign_clusters(e_pool(spark, sf), CentroidModel(np.eye(64)[:3])))
    assert "Exchange" not in a and "PushedFilters" in a


@pytest.mark.parametrize("name, column", [("s1_gray_luma", "gray"), ("s2_normalize", "vec")])
def test_rounded_vectors_keep_the_sign_of_zero(spark, tmp_path, name, column):
    row = [0.6, -0.8, -1e-7, 1e-7, -0.0, 0.0, -4.9e-7, -5.1e-7] + [0.0] * 56
    rows = spark.createDataFrame([(0, row, 1), (1, row[::-1], 2)], "vec_id long, embedding array<float>, label int")
    rows.write.parquet(f"{tmp_path}/embeddings.parquet")
    got = {r["sample_id"]: list(map(repr, r[column])) for r in entry.queries()[name](spark, str(tmp_path)).collect()}
    con = duckdb.connect()
    con.execute(f"CREATE VIEW embeddings AS SELECT * FROM '{tmp_path}/embeddings.parquet/*.parquet'")
    cursor = con.execute(entry.oracle_sql()[name])
    names = [c[0] for c in cursor.description]
    want = {r[names.index("sample_id")]: list(map(repr, r[names.index(column)])) for r in cursor.fetchall()}
    assert "-0.0" in want[0] and got == want
