import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from subsetlab.llm.graph import components
from subsetlab.llm.near_dedup import across_components, drop_near_copies, near_components, op1_minhash_near_dedup, sketches


def shingles(text, k):
    words = re.findall(r"[^\x20\x09-\x0D]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or ""))
    return {tuple(words[i : i + k]) for i in range(max(1, len(words) - k + 1))} if words else set()


def brute(docs, k, percent):
    sets = {d: shingles(t, k) for d, t in docs.items()}
    holders = {}
    for d, s in sets.items():
        for x in s:
            holders.setdefault(x, []).append(d)
    head = {d: d for d in docs}

    def find(x):
        while head[x] != x:
            x = head[x]
        return x

    seen = {(a, b) for ds in holders.values() for i, a in enumerate(ds) for b in ds[i + 1 :]}
    for a, b in seen:
        both = len(sets[a] & sets[b])
        if 100 * both >= percent * len(sets[a] | sets[b]):
            a, b = sorted((find(a), find(b)))
            head[b] = a
    return {d: (len(sets[d]), find(d), find(d) == d) for d in docs}


@pytest.mark.parametrize("where", ["sf0.01"])
def test_query_against_brute_force(spark, where):
    path = f"/root/testdata/{where}"
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{path}/documents.parquet").collect()}
    got = {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in op1_minhash_near_dedup(spark, path).collect()}
    assert got == brute(docs, 3, 85)


def test_star_chain_and_edge_cases(spark):
    words = [f"w{i}" for i in range(120)]
    docs = {50: " ".join(words)}
    for i in range(12):  # copies that each differ from the original, but more from one another
        own = list(words)
        own[i * 10 + 3] = own[i * 10 + 7] = f"x{i}"
        docs[i] = " ".join(own)
    docs |= {60: "", 61: "   ", 62: "one two", 63: "ONE  two", 64: "one", 65: " ".join(words).upper(), 66: "é " * 30_000, 67: "é " * 30_000}
    rows = [(d, t, 0) for d, t in docs.items()] + [(68, None, 0), (None, "one two", 0), (62, "one two", 0)]
    df = spark.createDataFrame(rows, "doc_id long, text string, n long")
    got = near_components(spark, df, 3, 85).collect()
    assert len(got) == len(rows)
    expected = brute({d: t for d, t, _ in rows if d is not None}, 3, 85)
    for r in got:
        assert (r.n_shingles, r.component_id, r.kept) == (expected[r.doc_id] if r.doc_id is not None else (1, None, True))
    left = drop_near_copies(spark, df, 3, 85)
    assert left.columns == df.columns
    assert sorted(r.doc_id for r in left.filter("doc_id IS NOT NULL").collect()) == sorted([d for d, v in expected.items() if v[2]] + [62])
    assert near_components(spark, df.limit(0)).count() == 0


def test_links_outside_of_every_leader(spark):
    docs = {}
    for g in range(6):  # x and y are similar, but every leader lacks seven of their words, and with each alone they might not be
        word = lambda c, n: [f"g{g}{c}{i}" for i in range(n)]  # noqa: B023, E731
        core, left, right = word("c", 92), word("l", 6), word("r", 6)
        docs[1000 * g], docs[1000 * g + 1] = core + left + word("x", 2), core + right + word("y", 2)
        for i in range(13):
            lead = core[: 7 * i] + core[7 * i + 7 :] + left + right + word(f"o{i}-", 3)
            for j in range(7):
                docs[1000 * g + 10 * i + j + 10] = lead[:98] + word(f"z{i}-{j}-", 2) if j else lead
    docs = {d: " ".join(w) for d, w in docs.items()}
    got = near_components(spark, spark.createDataFrame(list(docs.items()), "doc_id long, text string"), 1, 85).collect()
    want = brute(docs, 1, 85)
    assert all(want[1000 * g + 1][1] == 1000 * g for g in range(6))
    assert {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in got} == want


def test_pairs_of_a_bucket_in_blocks(spark):
    rng = np.random.default_rng(5)
    sets = {i: np.sort(rng.choice(60, rng.integers(30, 45), replace=False).astype(np.uint64) * np.uint64(2**57 + 2**53)) for i in range(70)}
    sets[70] = np.arange(0, 90_000, dtype=np.uint64)  # counts over a byte
    sets[71] = np.arange(9, 90_000, dtype=np.uint64)
    rows = [(4, len(sets), i, len(s), i % 9 if i < 70 else i, bytearray(s.tobytes())) for i, s in sets.items()]
    rows = [(*r, [1], [2]) for r in rows]
    df = spark.createDataFrame(rows, "key long, c long, id long, n long, comp long, hashes binary, ga array<long>, gb array<long>")
    members = df.drop("hashes").join(sketches(df.select("id", "hashes")), "id")
    similar = {(a, b) for _, _, a, n, p, *_ in rows for _, _, b, m, q, *_ in rows if a < b and p != q and 100 * len(np.intersect1d(sets[a], sets[b])) >= 50 * len(np.union1d(sets[a], sets[b]))}
    assert len(similar) > 100 and (70, 71) in similar
    for block in (7, 1000):
        got = across_components(members, 50, 0, block).collect()
        assert similar <= {(r.a, r.b) for r in got} and all(r.a < r.b and (r.n, r.m) == (len(sets[r.a]), len(sets[r.b])) for r in got)


@pytest.mark.parametrize(("k", "percent", "common", "own", "shared"), [(1, 85, 820, 100, 55), (5, 80, 820, 140, 60)])
def test_a_family_of_templates(spark, k, percent, common, own, shared):
    """Every text holds the template; pairs that also share some words are similar, all others are just not."""
    word = lambda c, n: [f"{c}{i}" for i in range(n)]
    docs = {}
    for p in range(200):
        for side in (0, 1):
            docs[2 * p + side] = " ".join(word("t", common) + word(f"p{p}-", shared) + word(f"s{p}.{side}-", own - shared))
    got = near_components(spark, spark.createDataFrame(list(docs.items()), "doc_id long, text string"), k, percent).collect()
    want = brute_of_pairs(docs, k, percent)
    assert len({v for v in want.values()}) == 200
    assert {r.doc_id: r.component_id for r in got} == want


def brute_of_pairs(docs, k, percent):
    sets = {d: shingles(t, k) for d, t in docs.items()}
    head = {d: d for d in docs}
    for a in docs:
        for b in docs:
            if a < b and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                head[b] = min(head[b], head[a])
    return head


def test_components_of_a_path(spark):
    n = 40
    edges = spark.range(n - 1).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    assert {tuple(r) for r in components(spark, edges).collect()} == {(i, 0) for i in range(n)}
