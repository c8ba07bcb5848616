import hashlib
import re

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from subsetlab.llm.exact_dedup import drop_exact_copies, exact_dedup
from subsetlab.llm.line_dedup import line_dedup
from subsetlab.llm.mphf import LineIndex, MinimalPerfectHash

ROWS = [(1, "a"), (2, None), (3, ""), (4, "a"), (5, "A"), (6, "a "), (7, "x" * 300_000), (8, "x" * 300_000), (4, "a"), (None, "a"), (None, "solo")]


@pytest.mark.parametrize("weak", [False, True])
def test_exact(spark, weak):
    df = spark.createDataFrame([(d, t, "z", 1) for d, t in ROWS], "doc_id long, text string, digest string, salt int")
    digest = (lambda c: F.lit("same")) if weak else (lambda c: F.sha2(c, 256))
    got = exact_dedup(spark, df, digest=digest).collect()
    by = {}
    for d, t in ROWS:
        by.setdefault(t or "", []).append(d)
    keep = {t: max((d for d in ds if d is not None), default=None) for t, ds in by.items()}
    want = [(d, keep[t or ""], len(by[t or ""]), d == keep[t or ""]) for d, t in ROWS]
    assert sorted(map(repr, ((r.doc_id, r.keep_id, r.group_size, r.kept) for r in got))) == sorted(map(repr, want))
    left = drop_exact_copies(spark, df)
    assert left.columns == df.columns and sorted(r.doc_id or -1 for r in left.collect()) == [-1, 3, 4, 4, 5, 6, 8]
    assert exact_dedup(spark, df.limit(0)).count() == 0


@settings(max_examples=40, deadline=None)
@given(st.sets(st.integers(0, 2**64 - 1), max_size=400))
def test_perfect_hash(keys):
    keys = np.array(sorted(keys), np.uint64)
    h = MinimalPerfectHash(keys, keys)
    assert sorted(h(keys, keys).tolist()) == list(range(len(keys)))
    index = LineIndex(keys, keys ^ np.uint64(9), np.full(len(keys), 70_000), np.arange(len(keys)))
    count, owner = index.probe(keys, keys ^ np.uint64(9))
    assert (count == 65535).all() and (owner == np.arange(len(keys))).all()
    assert not index.probe(keys, keys)[0].any()


def test_keys_that_agree_in_one_hash():
    keys, prints = np.repeat(np.arange(50, dtype=np.uint64), 4), np.tile(np.arange(4, dtype=np.uint64) << np.uint64(40), 50)
    h = MinimalPerfectHash(keys, prints)
    assert sorted(h(keys, prints).tolist()) == list(range(200))
    index = LineIndex(keys, prints, np.arange(200), np.arange(200))
    count, owner = index.probe(keys, prints)
    assert count.tolist() == owner.tolist() == list(range(200))
    assert not index.probe(keys, prints + np.uint64(1))[0].any()


def alternating(n):
    """A text of a and b whose two halves cancel out in polynomial hashes, and the text with both letters exchanged."""
    a, b = "a", "b"
    while len(a) < n:
        a, b = a + b, b + a
    return a, b


def test_unique_lines_of_like_structure_stay(spark):
    a, b = alternating(1024)
    df = spark.createDataFrame([(1, a), (2, b), (3, a)], "doc_id long, text string")
    assert {r.doc_id: r.n_dropped for r in line_dedup(spark, df).collect()} == {1: 0, 2: 0, 3: 1}


def brute_lines(docs, least=10):
    key = lambda x: "".join(c.lower() if c.isascii() else c for c in re.sub(r"^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$", "", x))
    first, holders = {}, {}
    for d, t in docs:
        for x in (t or "").split("\n"):
            if len(key(x)) >= least:
                first[key(x)] = min(d, first.get(key(x), d))
                holders.setdefault(key(x), set()).add(d)
    out = []
    for d, t in docs:
        lines = (t or "").split("\n")
        stay = [x for x in lines if not (len(holders.get(key(x), ())) > 1 and first[key(x)] != d)]
        out.append((d, len(lines), len(lines) - len(stay), hashlib.sha256("\n".join(stay).encode()).hexdigest()))
    return sorted(out)


@pytest.mark.parametrize("hot_share", [20_000, 3])
def test_lines(spark, hot_share):
    shared = "A line that many share"
    docs = [(i, f"own line of {i}\n  {shared.upper()}\t\nshort\n\n") for i in range(150)]
    docs += [(200, None), (201, ""), (202, "short\nshort"), (203, f"{shared}\n{shared}\nééééééééé\nééééééééé\x85"), (204, "ééééééééé\nééééééééé\x85"), (205, "x" * 200_000 + "\n" + shared), (-1, "own line of 7")]
    df = spark.createDataFrame([(d, t, 0) for d, t in docs], "doc_id long, text string, line long")
    got = line_dedup(spark, df, with_text=True, hot_share=hot_share, shards=3).collect()
    assert sorted((r.doc_id, r.n_lines, r.n_dropped, r.kept_sha256) for r in got) == brute_lines(docs)
    assert all(hashlib.sha256(r.kept_text.encode()).hexdigest() == r.kept_sha256 for r in got)
    nulls = spark.createDataFrame([(None, shared), (1, shared), (1, shared)], "doc_id long, text string")
    assert [r.n_dropped for r in line_dedup(spark, nulls).collect()] == [0, 0, 0]
    assert line_dedup(spark, df.limit(0)).count() == 0
