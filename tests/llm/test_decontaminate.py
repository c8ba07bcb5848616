import re
from collections import Counter

import numpy as np
import pytest

from subsetlab.llm.decontaminate import RADIUS, BenchmarkIndex, HammingIndex, contaminated, drop_contaminated, op7_simhash_decontamination, scan_batch


def grams(text, k=5):
    words = re.findall(r"(?:[a-z0-9]|[^\x00-\x7f])+", (text or "").lower() if (text or "").isascii() else "".join(c.lower() if c.isascii() else c for c in text))
    return [tuple(words[i : i + k]) for i in range(max(1, len(words) - k + 1))] if words else []


def brute(docs, items, least=0.8):
    out = {}
    for i, t in items:
        own = Counter(grams(t))
        size = own.total()
        for d, text in docs:
            g = grams(text)
            if not size or not set(own) & set(g):
                continue
            n = min(size, len(g))
            for s in range(len(g) - n + 1):
                w = Counter(g[s : s + n])
                both = (w & own).total()
                v = both / (n + size - both)
                if v >= least and v > out.get((d, i), (0,))[0]:
                    out[d, i] = (v, s)
    return out


@pytest.mark.parametrize("where", ["sf0.01"])
def test_query_against_brute_force(spark, where):
    path = f"/root/testdata/{where}"
    read = lambda n: [tuple(r)[:2] for r in spark.read.parquet(f"{path}/{n}.parquet").collect()]
    got = {(r.doc_id, r.item_id): (r.similarity, r.start_word) for r in op7_simhash_decontamination(spark, path).collect()}
    want = brute(read("documents"), read("benchmark"))
    assert want
    assert got == want


@pytest.mark.parametrize("n", [0, 1, 300, 3000])
def test_every_fingerprint_within_the_radius(n):
    rng = np.random.default_rng(5)
    stored = rng.integers(0, 1 << 16, (n, 8), dtype=np.uint16)
    queries = stored[rng.integers(0, n, 600)].copy() if n else rng.integers(0, 1 << 16, (5, 8), dtype=np.uint16)
    for q in queries:
        for bit in rng.choice(128, rng.integers(0, 45), replace=False):
            q[bit // 16] ^= np.uint16(1 << (bit % 16))
    distance = np.bitwise_count(queries[:, None, :] ^ stored[None, :, :]).sum(axis=2)
    want = set(zip(*(x.tolist() for x in np.nonzero(distance <= RADIUS)), strict=True))
    q, s, d = HammingIndex(stored).search(queries)
    assert set(zip(q.tolist(), s.tolist(), strict=True)) == want
    assert (distance[q, s] == d).all()


def test_near_copies_and_edge_cases(spark):
    words = [f"w{i}" for i in range(60)]
    item = " ".join(words)
    near = " ".join(["x", "y", *words[2:], "tail"])
    docs = [
        (1, f"Before, {item.upper()}! after", 0), (2, near, 0), (3, " ".join(words[:40]), 0), (4, " ".join(words[:55]), 0), (5, None, 0), (6, "", 0),
        (7, "one two", 0), (1, item, 0), (8, "a b " * 50_000 + item, 0), (None, item, 0),
    ]
    df = spark.createDataFrame(docs, "doc_id long, text string, item_id long")
    items = [(10, item), (11, None), (12, "One two"), (None, item), (13, "")]
    bench = spark.createDataFrame([(i, t, 0) for i, t in items], "item_id long, text string, doc_id long")
    for shard in (50_000, 2):
        got = sorted(((r.doc_id or -1), r.item_id) for r in contaminated(spark, df, bench, shard_items=shard).collect())
        assert got == [(-1, 10), (1, 10), (1, 10), (2, 10), (4, 10), (7, 12), (8, 10)]
    assert sorted(r.doc_id or -1 for r in drop_contaminated(spark, df, bench).collect()) == [-1, 3, 5, 6]
    assert contaminated(spark, df.limit(0), bench).count() == contaminated(spark, df, bench.limit(0)).count() == 0


def test_repeated_shingles_weigh_like_others(spark):
    words = [f"w{i}" for i in range(124)]
    items = [(1, " ".join(words + ["r"] * 14)), (2, " ".join(["n"] * 90)), (3, " ".join(["m", "k"] * 30))]
    docs = [(1, " ".join(words + ["q"] * 14)), (2, " ".join(["z"] * 9 + ["n"] * 85)), (3, " ".join(["n"] * 60)), (4, " ".join(["k", "m"] * 500)), (5, " ".join(words[:90] + ["q"] * 40))]
    got = {(r.doc_id, r.item_id): (r.similarity, r.start_word) for r in contaminated(spark, spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")).collect()}
    assert got == brute(docs, items) and {(1, 1), (2, 2), (4, 3)} <= got.keys()


def test_recall_at_the_threshold():
    texts = [" ".join(f"i{k}w{i}" for i in range(100)) for k in range(1500)]
    index = BenchmarkIndex(list(range(len(texts))), texts)
    near = [t.rsplit(" ", 10)[0] + " " + " ".join(f"x{k}y{i}" for i in range(10)) for k, t in enumerate(texts)]  # similarity 86 / 106
    raw = [t.encode() for t in near]
    offs = np.concatenate(([0], np.cumsum([len(r) for r in raw]))).astype(np.int64)
    rows = scan_batch(index, list(range(len(near))), np.frombuffer(b"".join(raw), np.uint8), offs, 0.8)
    assert {r[:2] for r in rows} == {(k, k) for k in range(len(texts))}


def test_index_of_long_items():
    index = BenchmarkIndex([1], [" ".join(f"v{i % 700}" for i in range(2000))])
    assert index.similarity(np.repeat(index.items[0][0], index.items[0][1]), 0) == 1.0
