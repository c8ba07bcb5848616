import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from subsetlab.functions.udf import bytes_entropy, counts_entropy
from subsetlab.operators import entropy as H
from subsetlab.schemas import BYTES, VECTOR, SampleSpec, check_contract

EXAMPLES = [([7, 7, 7, 7], 0.0), ([0, 0, 255, 255], 0.693147), ([0, 0, 0, 255], 0.562335), ([10, 10, 20, 30], 1.039721), ([0, 85, 170, 255], 1.386294)]


def test_worked_examples():
    data = np.array([x for levels, _ in EXAMPLES for x in levels] , np.uint8)
    h = bytes_entropy(data, np.arange(0, 4 * len(EXAMPLES) + 1, 4))
    assert np.round(h, 6).tolist() == [x for _, x in EXAMPLES]
    assert math.copysign(1, h[0]) == 1
    assert bytes_entropy(np.zeros(0, np.uint8), np.array([0, 0])).tolist() == [0.0]


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 9), min_size=1, max_size=60), st.randoms())
def test_invariants(levels, rng):
    h = counts_entropy(np.bincount(levels, minlength=10)[None, :])[0]
    mixed = [9 - x for x in levels]
    rng.shuffle(mixed)
    assert 0 <= h <= math.log(10) + 1e-12
    assert h == pytest.approx(counts_entropy(np.bincount(mixed, minlength=10)[None, :])[0])


def scored(spark):
    return spark.createDataFrame([(i, h) for i, (_, h) in enumerate(EXAMPLES, 1)], "sample_id long, entropy double")


def test_threshold_keeps_equality(spark):
    assert sorted(r.sample_id for r in H.prune_by_threshold(scored(spark), 0.693147).collect()) == [2, 4, 5]


def test_top_share_is_nested(spark):
    kept = {bp: {r.sample_id for r in H.prune_top_fraction(scored(spark), bp).collect()} for bp in (0, 2000, 4000, 6000, 10_000)}
    assert kept[6000] == {5, 4, 2} and kept[0] == set()
    assert all(kept[a] <= kept[b] for a, b in ((0, 2000), (2000, 4000), (4000, 6000), (6000, 10_000)))
    assert H.entropy_cutoff(scored(spark), 6000) == 0.693147


def test_engines_agree_and_nulls_have_no_entropy(spark):
    rows = spark.createDataFrame([(1, None), (2, ""), (3, "aabb"), (4, "ü"), (5, "x" * 90_000 + "y")], "sample_id long, payload string")
    a, b = ({r.sample_id: r.entropy for r in H.sample_entropy(rows, BYTES, e).collect()} for e in ("arrow", "sql"))
    assert a == pytest.approx(b) and a[1] == a[2] == 0 and a[3] == pytest.approx(math.log(2))


def test_vector_levels_clamp_and_own_range(spark):
    rows = spark.createDataFrame([(1, [-9.0, 9.0, 0.0, 0.0]), (2, [5.0, 5.0]), (3, None)], "sample_id long, payload array<double>")
    fixed = {r.sample_id: r.entropy for r in H.sample_entropy(rows, VECTOR).collect()}
    own = {r.sample_id: r.entropy for r in H.sample_entropy(rows, VECTOR, lo=None, hi=None).collect()}
    assert fixed[1] == pytest.approx(1.039721, abs=1e-6) and fixed[2] == fixed[3] == own[2] == own[3] == 0
    assert {r.sample_id: r.entropy for r in H.sample_entropy(rows.filter("payload IS NOT NULL"), VECTOR, "sql").collect()}[1] == pytest.approx(fixed[1])


def test_contract(spark):
    df = spark.createDataFrame([(1, "a"), (1, "b")], "doc_id long, text string")
    bound = SampleSpec("documents", "doc_id", "text", BYTES).bind(df)
    check_contract(bound)
    with pytest.raises(ValueError, match="repeated"):
        check_contract(bound, unique=True)
    with pytest.raises(ValueError, match="missing"):
        check_contract(df)
    with pytest.raises(ValueError, match="null"):
        check_contract(bound.unionByName(bound.withColumn("sample_id", F.lit(None).cast("long"))))
