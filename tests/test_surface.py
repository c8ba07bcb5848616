import datetime as dt
import math
import struct
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from subsetlab.operators import baselines as B
from subsetlab.operators import features as F_
from subsetlab.operators import measures as M
from subsetlab.operators import pairs as PR
from subsetlab.operators.centroids import CentroidModel, reference_bank
from subsetlab.operators.features import hashed_tokens
from subsetlab.session import get_session
from subsetlab.sources import tables as T
from subsetlab.streaming import streams as ST


def test_session_is_shared(spark):
    assert get_session() is spark


def test_read_write(spark, tmp_path):
    df = spark.range(10).select(F.col("id").alias("sample_id"), (F.col("id") % 3).alias("cluster_id"))
    T.write(df, str(tmp_path / "p"), partition_by=("cluster_id",))
    assert spark.read.parquet(str(tmp_path / "p")).filter("cluster_id = 1").count() == 3
    with pytest.raises(ValueError, match="schema"):
        T.read(spark, str(tmp_path / "p"), "csv")
    T.write_manifest(df, str(tmp_path / "m"))
    assert spark.read.parquet(str(tmp_path / "m")).columns == ["sample_id"]
    samples = df.withColumn("payload", F.lit("x"))
    assert T.materialize_selection(samples, df.filter("sample_id < 4")).count() == 4


def test_raw_files(spark, tmp_path):
    for i in range(3):
        (tmp_path / f"{i}.raw").write_bytes(bytes(range(i * 20 + 1)))
    images = T.read_files(spark, str(tmp_path), "*.raw")
    from subsetlab.operators.entropy import sample_entropy

    got = sorted(r.entropy for r in sample_entropy(images).collect())
    assert got == pytest.approx([0, math.log(21), math.log(41)])


def png(path, width, rows, color):
    """A PNG file of 8-bit rows; color 0 is grey, 2 is red, green, blue, 6 has a fourth band."""
    chunk = lambda kind, data: struct.pack(">I", len(data)) + kind + data + struct.pack(">I", zlib.crc32(kind + data))
    head = struct.pack(">IIBBBBB", width, len(rows), 8, color, 0, 0, 0)
    path.write_bytes(b"\x89PNG\r\n\x1a\n" + chunk(b"IHDR", head) + chunk(b"IDAT", zlib.compress(b"".join(b"\0" + bytes(r) for r in rows))) + chunk(b"IEND", b""))


def test_images_are_decoded_to_grey_levels(spark, tmp_path):
    from subsetlab.operators.entropy import sample_entropy

    png(tmp_path / "a.png", 4, [[0, 0, 255, 255], [0, 0, 255, 255]], 0)
    png(tmp_path / "b.png", 2, [[255, 0, 0, 0, 255, 0], [0, 0, 255, 10, 10, 10]], 2)
    png(tmp_path / "c.png", 2, [[8, 16, 24, 32, 40, 40, 40, 40]], 6)
    (tmp_path / "d.png").write_bytes(b"no image")
    images = T.read_images(spark, str(tmp_path))
    got = {r.bands: (list(r.payload), r.height, r.width) for r in images.collect()}
    assert got == {1: ([0, 0, 255, 255] * 2, 2, 4), 3: ([76, 150, 29, 10], 2, 2), 4: ([20, 40], 1, 2)}
    entropies = {r.sample_id: r.entropy for r in sample_entropy(images).collect()}
    assert sorted(entropies.values()) == pytest.approx([math.log(2), math.log(2), math.log(4)])
    red = T.read_images(spark, str(tmp_path), "b.png", {3: (1.0, 0.0, 0.0)}).first()
    assert list(red.payload) == [255, 0, 0, 10]


def test_any_encoder_plugs_in(spark):
    class MeanAndSpread:
        size = 2

        def __call__(self, payloads):
            return np.array([[np.nan] * 2 if not p else [np.mean(list(p)), np.std(list(p))] for p in payloads.to_pylist()])

    df = spark.createDataFrame([(1, bytearray([1, 3])), (2, bytearray()), (3, None)], "sample_id long, payload binary")
    assert {r.sample_id: r.vec for r in F_.encode(df, MeanAndSpread()).collect()} == {1: [2.0, 1.0], 2: None, 3: None}


def test_broken_vectors_have_no_levels(spark):
    from subsetlab.operators.entropy import sample_entropy
    from subsetlab.schemas import VECTOR

    nan, inf = float("nan"), float("inf")
    rows = [(1, [0.1, 0.2, -0.3]), (2, [nan, 0.1, 0.2]), (3, [0.1, None, 0.2]), (4, [inf, 0.1, 0.2]), (5, None), (6, [])]
    for engine in ("arrow", "sql"):
        for lo in (-0.5, None):
            got = {r.sample_id: r.entropy for r in sample_entropy(spark.createDataFrame(rows, "sample_id long, payload array<double>"), VECTOR, engine, lo=lo).collect()}
            assert got[1] > 0.6 and [got[i] for i in range(2, 7)] == [0] * 5


def test_stream_state_keeps_large_ids(spark, tmp_path):
    src, out, big = str(tmp_path / "src"), str(tmp_path / "out"), 2**62 + 1
    for k in range(2):
        spark.createDataFrame([(big + 2 * k, 0, 0.5), (big + 2 * k + 1, 0, 0.1)], "sample_id long, cluster_id int, sim double").coalesce(1).write.mode("append").parquet(src)
        stream = spark.readStream.schema("sample_id long, cluster_id int, sim double").parquet(src)
        got = []
        ST.drain_batches(ST.top_q_stateful(stream, 2), out, lambda df, _: got.extend(df.collect()), "update")
    assert {r.sample_id for r in got} == {big, big + 2}


def test_bucketed_join_needs_no_exchange(spark):
    df = spark.range(1000).withColumnRenamed("id", "k")
    for name in ("bucket_a", "bucket_b"):
        T.write_bucketed(df.withColumn(name, F.col("k") * 2), name, 4, "k")
    try:
        joined = spark.table("bucket_a").hint("merge").join(spark.table("bucket_b"), "k")
        assert "Exchange" not in joined._jdf.queryExecution().executedPlan().toString()
        assert joined.count() == 1000
    finally:
        for name in ("bucket_a", "bucket_b"):
            spark.sql(f"DROP TABLE {name}")


SCHEMA = "event_id long, ts timestamp, user_id long, event_type string"


def files(spark, path, rows):
    spark.createDataFrame(rows, SCHEMA).coalesce(1).write.mode("append").parquet(path)


def at(hour, minute=0):
    return dt.datetime(2024, 1, 1, hour, minute)


def test_late_rows_are_dropped_behind_the_watermark(spark, tmp_path):
    src, out = str(tmp_path / "src"), str(tmp_path / "out")
    stream = lambda: spark.readStream.schema(SCHEMA).parquet(src)
    frame = lambda: ST.type_entropy(stream(), F.window("ts", "1 hour"), ["a", "b"], "1 hour")
    files(spark, src, [(1, at(1), 1, "a"), (2, at(1, 30), 1, "b"), (3, at(9), 1, "a")])
    ST.drain(frame(), out)
    files(spark, src, [(4, at(1, 45), 1, "b"), (5, at(12), 1, "a")])  # the first is late by more than an hour
    ST.drain(frame(), out)
    rows = {r.start.hour: (r.n, round(r.entropy, 6)) for r in spark.read.parquet(out).collect()}
    assert rows == {1: (2, 0.693147), 9: (1, 0.0)}


def test_restart_repeats_nothing(spark, tmp_path):
    src, out = str(tmp_path / "src"), str(tmp_path / "out")
    for k in range(3):
        files(spark, src, [(k, at(k), 1, "a")])
        ST.drain(ST.deduplicated(spark.readStream.schema(SCHEMA).parquet(src), ["event_id"]), out)
    assert sorted(r.event_id for r in spark.read.parquet(out).collect()) == [0, 1, 2]


def test_top_q_merge_is_idempotent(spark):
    held = []
    fn = ST.top_q_sink(lambda df: held.append(T.stage(spark, df, "t")), lambda: held[-1] if held else None, 2)
    batch = spark.createDataFrame([(i, i % 2, i / 10) for i in range(8)], "sample_id long, cluster_id int, sim double")
    for b in (batch.filter("sample_id < 5"), batch, batch):
        fn(b, 0)
    assert sorted(r.sample_id for r in held[-1].collect()) == [4, 5, 6, 7]


def test_engines_of_hashed_tokens_agree(spark):
    df = spark.createDataFrame([(1, "A b  b\nc"), (2, ""), (3, None)], "sample_id long, payload string")
    a, b = ({r.sample_id: r.vec for r in hashed_tokens(df, 8, e).collect()} for e in ("arrow", "sql"))
    assert a[1] == pytest.approx(b[1]) and a[2] is a[3] is b[2] is b[3] is None


def vectors(spark, rows):
    return spark.createDataFrame([(i, [float(x) for x in v], i % 2) for i, v in enumerate(rows)], "sample_id long, vec array<double>, label int")


def test_retrieval_blocks_do_not_matter(spark):
    pool, ref = vectors(spark, [(1, i / 7) for i in range(20)]), vectors(spark, [(i / 5, 1) for i in range(7)])
    a, b = ({tuple(r) for r in PR.nearest_rows(pool, ref, 3, block).collect()} for block in (2, 100))
    assert a == b and len(a) == 21
    assert {r.sample_id: round(r.best, 9) for r in PR.best_similarity(pool, ref, 2).collect()} == {r.sample_id: round(r.best, 9) for r in PR.best_similarity(pool, ref).collect()}


def test_similar_pairs_against_all_pairs(spark):
    rng = np.random.default_rng(7)
    centre = rng.normal(size=(6, 5))
    rows = np.concatenate([centre[rng.integers(0, 6, 300)] + rng.normal(size=(300, 5)) * 0.15, np.zeros((1, 5))])
    df = vectors(spark, rows)
    z = rows[:300] / np.linalg.norm(rows[:300], axis=1, keepdims=True)
    sim = np.round(z @ z.T, 9)
    for least in (0.99, 0.9, 0.2):
        want = {(a, b) for a, b in zip(*(x.tolist() for x in np.nonzero(sim >= least)), strict=True) if a < b}
        for pivots, block in ((3, 1000), (40, 17)):
            found = [(r.a, r.b) for r in PR.similar_pairs(df, least, pivots, block).collect()]
            assert len(found) == len(set(found)) and set(found) == want
    assert PR.similar_pairs(df.limit(0), 0.9).count() == 0
    left = {r.sample_id for r in PR.drop_near_copies(df, 0.99).collect()}
    assert left == {i for i in range(301)} - {b for _, b in zip(*(x.tolist() for x in np.nonzero(np.triu(sim >= 0.99, 1))), strict=True)}


def test_scores_of_any_scale_rank(spark):
    from subsetlab.operators.select import SelectionPlanner

    samples = spark.range(200).withColumnRenamed("id", "sample_id")
    for scale in (1e-3, 1.0, 1e12):
        scores = samples.withColumn("score", F.floor(F.col("sample_id") / 2) * scale).unionByName(spark.createDataFrame([(500, None), (501, float("nan"))], "sample_id long, score double"))
        for planner in (SelectionPlanner(), SelectionPlanner(sort_rows=0, boundary_rows=1)):
            assert {r.sample_id for r in B.score_ranked(samples, scores, 20, planner).collect()} == set(range(180, 200))
    flat = samples.withColumn("score", F.lit(0.5))
    first = {r.sample_id for r in B.score_ranked(samples, flat, 20).collect()}
    assert first == {r.sample_id for r in B.score_ranked(samples, flat, 20, SelectionPlanner(sort_rows=0, boundary_rows=1)).collect()}
    assert first == {r.sample_id for r in B.random_rows(samples, 20).collect()}


def test_measures_in_words(spark):
    one = vectors(spark, [(1, 0), (1, 0.001), (0, 1)])
    assert M.redundancy(one, 0.99).first().with_neighbour == 2
    even = spark.createDataFrame([(i, i % 4) for i in range(40)], "sample_id long, g int")
    r = M.balance(even, "g", 4).first()
    assert (r.evenness, r.gini, r.min_share) == pytest.approx((1, 0, 0.25))
    r = M.balance(even.filter("g = 0"), "g", 4).first()
    assert (r.evenness, r.gini, r.min_share) == pytest.approx((0, 0.75, 0))
    results = spark.createDataFrame([("two", 28.46), ("next", 39.34), ("other", 45.0)], "method string, v double")
    assert M.improvement(results, "v", "two").first().improvement == pytest.approx(0.277, abs=1e-3)


def test_bank_needs_a_choice(spark):
    with pytest.raises(ValueError, match="no bank"):
        reference_bank({})
    assert CentroidModel.__doc__


def test_wide_angles_copy_no_rows(spark, monkeypatch):
    rng = np.random.default_rng(3)
    rows = rng.normal(size=(900, 4))
    df = vectors(spark, rows)
    z = rows / np.linalg.norm(rows, axis=1, keepdims=True)
    sim = np.round(z @ z.T, 9)
    written, keep = [], PR.stage

    def counted(session, part, name):
        out = keep(session, part, name)
        written.append(out.count())
        return out

    monkeypatch.setattr(PR, "stage", counted)
    monkeypatch.setattr(PR, "BLOCK_BYTES", 1)
    monkeypatch.setattr(PR, "TILE_REFS", 400)  # blocks of 400 rows
    monkeypatch.setattr(PR, "TILE_ROWS", 70)
    want = np.triu(sim >= 0.96, 1)
    found = [(r.a, r.b) for r in PR.similar_pairs(df, 0.96, 16, 10).collect()]
    assert len(found) == len(set(found)) == want.sum() and all(want[p] for p in found)
    assert sum(written) <= 900 + len(found)
    assert {r.sample_id for r in PR.similar_rows(df, 0.96, False, 16, 10).collect()} == set(np.flatnonzero((want | want.T).any(axis=0)).tolist())
    assert {r.sample_id for r in PR.similar_rows(df, 0.96, True, 16, 10).collect()} == set(np.flatnonzero(want.any(axis=0)).tolist())
    assert PR.similar_rows(df.limit(0), 0.96).count() == 0


def test_running_top_equals_sorting_everything(monkeypatch):
    import pyarrow as pa

    rng = np.random.default_rng(1)
    u = rng.integers(-2, 3, size=(400, 4)).astype(float)  # many ties
    u = u[(u != 0).any(axis=1)]
    u /= np.linalg.norm(u, axis=1, keepdims=True)
    z, ids, mine = u[rng.choice(len(u), 150)], np.arange(1000, 1150), rng.permutation(len(u))
    monkeypatch.setattr(PR, "TILE_ROWS", 50)
    monkeypatch.setattr(PR, "TILE_REFS", 70)
    sim = np.round(z @ u.T, 9)
    order = np.lexsort((np.broadcast_to(mine, sim.shape), -sim), axis=1)[:, :4]
    for size in (3, 64, 1000):
        parts = ((mine[i : i + size], u[i : i + size]) for i in range(0, len(u), size))
        t = pa.Table.from_batches(PR.running_top(ids, z, parts, 4, True)).to_pylist()
        assert {(r["ref_id"], r["sample_id"]) for r in t if r["ref_id"] is not None} == {(int(ids[r]), int(mine[c])) for r in range(len(ids)) for c in order[r]}
        assert {r["sample_id"]: round(r["sim"], 9) for r in t if r["ref_id"] is None} == dict(zip(mine.tolist(), sim.max(axis=0).tolist(), strict=True))


def test_curves_multiply_pool_and_reference_once(spark, sf, monkeypatch):
    from subsetlab.catalog.workload import bench
    from subsetlab.plans import workloads as WL

    passes, run = [], PR._by_blocks
    monkeypatch.setattr(PR, "_by_blocks", lambda *a, **kw: passes.append(1) or run(*a, **kw))
    b = bench(spark, sf)
    curves = WL.convergence_curves(b, [5000, 9000], 4, 2, 16, ("retrieval",))
    assert {r.method for r in curves.collect()} == {"5000:retrieval", "9000:retrieval"} and len(passes) == 1
    for rho in (5000, 9000):
        budget = WL.budget_of(b.n, rho)
        sim = {r.sample_id: r.best for r in PR.best_similarity(b.cand, b.ref).collect()}
        hits = {r.sample_id for r in PR.nearest_rows(b.cand, b.ref, 4).collect()}
        first = sorted(sim, key=lambda i: (-round(sim[i], 9) - 10 * (i in hits), i))[:budget]
        assert {r.sample_id for r in B.retrieval_nearest(b.cand, b.ref, budget).collect()} == set(first)
