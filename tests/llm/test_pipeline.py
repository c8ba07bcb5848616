import pytest

from subsetlab.llm.common import materialize
from subsetlab.llm.quality import train

from .test_decontaminate import brute as leaks
from .test_near_dedup import brute as groups
from .test_packing import check
from .test_quality import slow_score


def test_pipeline_against_brute_force(spark):
    import corpus_pipeline

    path = "/root/testdata/sf0.01"
    docs, labels = (spark.read.parquet(f"{path}/{n}.parquet") for n in ("documents", "labels"))
    field = train(docs, labels)
    scores = {r.doc_id: (slow_score(r.text, field), r.text) for r in docs.collect()}
    assert min(abs(s - 0.3) for s, _ in scores.values()) > 1e-4  # no document so close to the threshold that rounding decides
    good = {d: t for d, (s, t) in scores.items() if s >= 0.3}
    last = {}
    for d, t in good.items():
        last[t] = max(d, last.get(t, -1))
    one = {d: t for t, d in last.items()}
    kept = {d: one[d] for d, v in groups(one, 5, 80).items() if v[2]}
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{path}/benchmark.parquet").collect()]
    bad = {d for d, _ in leaks(list(kept.items()), items)}
    rows = corpus_pipeline.run(spark, path).collect()
    assert {r.doc_id for r in rows} == kept.keys() - bad
    assert bad and len(kept) < len(one) < len(good) < docs.count()
    check(rows, 2048)


def test_stages_keep_columns_and_take_empty_tables(spark, sf):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf}/documents.parquet").selectExpr("*", "1 AS id", "'x' AS digest").limit(0)
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns and out.count() == 0
    assert materialize(spark, corpus_pipeline.STAGES[-1][1](spark, docs, sf), "t").count() == 0


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty texts, repeated rows, a very long text and names that the operators use themselves."""
    prose = "The river runs past the old mill, and nobody has counted its stones. "
    own = lambda k: " ".join(f"Sentence {k} number {i} says something of its own kind." for i in range(30))
    rows = [(1, None), (2, ""), (3, own(3)), (3, own(3)), (4, own(3)), (5, own(3) + " End."), (None, own(9)), (6, prose * 20_000), (7, own(7)), (7, own(8))]
    rows = [(d, t, None, "s", len(t or ""), 1, "h", True) for d, t in rows]
    return materialize(spark, spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, id int, digest string, kept boolean"), "odd")


@pytest.mark.parametrize(("stage", "left"), [
    ("exact_dedup", [None, 2, 4, 5, 6, 7, 7]), ("near_dedup", [None, 1, 2, 3, 3, 6, 7, 7]), ("decontamination", [None, 1, 2, 3, 3, 4, 5, 6, 7, 7]),
])
def test_odd_rows(spark, sf, odd, stage, left):
    import corpus_pipeline

    out = dict(corpus_pipeline.STAGES)[stage](spark, odd, sf)
    assert out.columns == odd.columns
    assert sorted((r.doc_id for r in out.collect()), key=lambda d: (d is not None, d)) == left


def test_odd_rows_of_the_ends(spark, sf, odd):
    import corpus_pipeline

    stages = dict(corpus_pipeline.STAGES)
    scored = stages["quality"](spark, odd, sf)
    assert scored.columns == odd.columns and {3, 4, 5, 7} <= {r.doc_id for r in scored.collect()}
    packed = stages["packing"](spark, odd, sf).collect()
    assert {r.doc_id for r in packed} == {None, *range(1, 8)} and check(packed, 2048) == -(-sum(r.length for r in packed) // 2048)
