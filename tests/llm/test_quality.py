import re
import zlib
from itertools import product

import numpy as np

from subsetlab.llm.quality import N_FEATURES, LineField, keep_good, line_features, op6_line_field_quality, quality_scores, train


def buffer(texts):
    raw = [t.encode() for t in texts]
    return np.frombuffer(b"".join(raw), np.uint8), np.concatenate(([0], np.cumsum([len(r) for r in raw]))).astype(np.int64)


def test_marginals_against_enumeration():
    rng = np.random.default_rng(1)
    first = np.array([0, 1, 5, 8])
    x = rng.normal(size=(8, N_FEATURES)).astype(np.float32)
    field = LineField(rng.normal(size=N_FEATURES) / 5, rng.normal(size=(2, 2)))
    got = field.marginals(x, first)
    u = x @ field.w
    for a, b in zip(first[:-1], first[1:], strict=True):
        total, good = 0.0, np.zeros(b - a)
        for path in product((0, 1), repeat=int(b - a)):
            p = np.exp(sum(u[a + t] * y for t, y in enumerate(path)) + sum(field.moves[y, z] for y, z in zip(path, path[1:], strict=False)))
            total += p
            good += p * np.array(path)
        assert np.allclose(got[a:b], good / total)


def test_gradient_against_differences():
    rng = np.random.default_rng(2)
    first = np.array([0, 1, 5, 8, 20])
    x, weight = rng.normal(size=(20, N_FEATURES)), np.repeat([1.0, 0.5, 2.0, 0.25], np.diff(first))
    y, theta, field = rng.integers(0, 2, 20), rng.normal(size=N_FEATURES + 4) / 3, LineField()
    value, grad = field.objective(theta, x, first, y, weight, 0.01)
    assert value < 0
    for k in range(len(theta)):
        step = np.zeros(len(theta))
        step[k] = 1e-5
        up, down = (field.objective(theta + d, x, first, y, weight, 0.01)[0] for d in (step, -step))
        assert abs((up - down) / 2e-5 - grad[k]) < 1e-6


def test_training_raises_the_likelihood_and_separates():
    rng = np.random.default_rng(4)
    first = np.arange(0, 121, 3)
    label = np.arange(40) % 2
    x = rng.normal(size=(120, N_FEATURES)).astype(np.float32)
    x[:, 5] += 3 * np.repeat(label, 3)
    field = LineField().fit(x, first, label, np.ones(40))
    start = LineField().objective(np.zeros(N_FEATURES + 4), x, first, np.repeat(label, 3), np.ones(120), 1e-3)[0]
    assert field.objective(np.append(field.w, field.moves), x, first, np.repeat(label, 3), np.ones(120), 1e-3)[0] > start
    assert ((field.marginals(x, first) > 0.5) == np.repeat(label, 3)).mean() > 0.95


def slow_score(text, field):
    """A document's score line by line: features counted in Python, marginals by summing over prefixes and suffixes."""
    import math

    def own(line):
        raw = line.encode()
        low = bytes(b + 32 if 65 <= b <= 90 else b for b in raw)
        words = [w for w in re.split(rb"[\x20\x09-\x0d]+", low) if w]
        caps, small, digits = sum(65 <= b <= 90 for b in raw), sum(97 <= b <= 122 or b > 127 for b in raw), sum(48 <= b <= 57 for b in raw)
        bars, bangs, signs, stops, blanks = (sum(chr(b) in kind for b in raw if b < 128) for kind in ("|", "!", "#$%&*@^~<>{}[]\\_=+", ".,;:?", " \t\n\x0b\x0c\r"))
        letters, full, n = max(caps + small, 1), max(len(raw), 1), max(len(words), 1)
        again = [sum(a == b for a, b in zip(words[lag:], words, strict=False)) / n for lag in (1, 2)]
        return [1, min(math.log1p(len(raw)) / 8, 1), not raw, caps / letters, caps > 0.6 * letters, digits / full, min(bars / n, 1), min(bangs / n, 1), min(signs / n / 3, 1),
                min(stops / n, 1), min(blanks / full, 1), min(full / n / 16, 1), min(n / 8, 1), bars > 0, bangs + signs > 0, *again]

    lines = text.split("\n")
    one, none = [own(x) for x in lines], [0.0] * 17
    u = []
    for i in range(len(lines)):
        x = one[i] + (one[i - 1] if i else none) + (one[i + 1] if i + 1 < len(lines) else none) + [i == 0, i + 1 == len(lines)]
        u.append(sum(float(a) * b for a, b in zip(x, field.w, strict=True)))
    m = field.moves

    def chain(scores, moves):
        out = [(0.0, scores[0])]
        for s in scores[1:]:
            out.append(tuple(y * s + float(np.logaddexp(out[-1][0] + moves[0][y], out[-1][1] + moves[1][y])) for y in (0, 1)))
        return out

    ahead, back = chain(u, m), chain(u[::-1], m.T)[::-1]
    good = [1 / (1 + math.exp(min(60, a[0] + b[0] - a[1] - b[1] + s))) for a, b, s in zip(ahead, back, u, strict=True)]
    size = [max(len(x.encode()), 1) for x in lines]
    return sum(g * n for g, n in zip(good, size, strict=True)) / sum(size)


def test_query_against_slow_scores(spark, sf):
    docs, labels = (spark.read.parquet(f"{sf}/{n}.parquet") for n in ("documents", "labels"))
    field, texts = train(docs, labels), {r.doc_id: r.text for r in docs.collect()}
    rows = op6_line_field_quality(spark, sf).collect()
    assert {r.doc_id for r in rows} == texts.keys()
    for r in rows:
        assert abs(r.score - slow_score(texts[r.doc_id], field)) < 1e-4
        assert r.predicted == int(r.score >= 0.3) and r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0)


def test_training_takes_no_held_out_and_no_endless_documents(spark):
    free = [i for i in range(200) if zlib.crc32(str(i).encode()) % 5]
    held = [i for i in range(200) if i not in free]
    rows = [(i, "Plain words here.\n" * 3 if i % 2 else "!!! ### 12|34\n" * 3, i % 2) for i in free[:60]]
    docs = spark.createDataFrame([r[:2] for r in rows], "doc_id long, text string")
    labels = spark.createDataFrame([(i, q) for i, _, q in rows], "doc_id long, quality int")
    base = train(docs, labels)
    more = [(held[0], "x\n" * 5, 1), (held[1], "y", 0), (free[61], "z\n" * 600, 1)]
    wide = train(docs.union(spark.createDataFrame([r[:2] for r in more], docs.schema)), labels.union(spark.createDataFrame([(i, q) for i, _, q in more], labels.schema)))
    assert np.allclose(base.w, wide.w) and np.allclose(base.moves, wide.moves)


def test_features_do_not_depend_on_neighbouring_rows():
    texts = ["", "One two\n\nTHREE!! | x", "é é é\n", "the the the"]
    x, size, first = line_features(*buffer(texts))
    for i, t in enumerate(texts):
        own = line_features(*buffer([t]))
        assert np.allclose(x[first[i] : first[i + 1]], own[0]) and (size[first[i] : first[i + 1]] == own[1]).all()


def test_held_out_accuracy(spark):
    path = "/root/testdata/sf0.01"
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{path}/labels.parquet").collect()}
    rows = op6_line_field_quality(spark, path).collect()
    assert len(rows) == 1000
    for r in rows:
        assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0)
        assert 0 <= r.score <= 1 and r.predicted == int(r.score >= 0.3)
    held = [(r.score, labels[r.doc_id]) for r in rows if r.held_out and r.doc_id in labels]
    good, bad = ([s for s, q in held if q == k] for k in (1, 0))
    assert np.mean([a > b for a in good for b in bad]) > 0.95
    assert np.mean([s >= 0.3 for s in good]) > 0.97


def test_ties_repeats_and_clashing_names(spark):
    docs = spark.createDataFrame([(1, "Same text.\n", True, 7), (1, "Same text.\n", True, 7), (2, "Same text.\n", None, 7)], "doc_id long, text string, held_out boolean, predicted int")
    labels = spark.createDataFrame([(1, 1), (1, 1), (3, 0)], "doc_id long, quality int")
    rows = quality_scores(spark, docs, labels, threshold=0.5).collect()
    assert len(rows) == 3 and len({r.score for r in rows}) == 1 and {r.predicted for r in rows} == {int(rows[0].score >= 0.5)}
    assert [r.held_out for r in rows if r.doc_id == 2] == [zlib.crc32(b"2") % 5 == 0]
    flat = quality_scores(spark, docs, labels.limit(0), threshold=0.5).collect()
    assert {(r.score, r.predicted) for r in flat} == {(0.5, 1)}  # a score at the threshold counts as good


def test_edge_cases(spark):
    docs = spark.createDataFrame([(1, None, 0.5), (2, "", 0.5), (2, "A line.\n" * 3000, 0.5), (None, "x", 0.5)], "doc_id long, text string, score double")
    none = spark.createDataFrame([], "doc_id long, quality int")
    rows = quality_scores(spark, docs, none).collect()
    assert len(rows) == 4 and all(r.score == 0.5 for r in rows)
    one = spark.createDataFrame([(1, 1), (2, None), (None, 0)], "doc_id long, quality int")
    assert keep_good(spark, docs, one).columns == docs.columns
    assert quality_scores(spark, docs.limit(0), one).count() == 0
