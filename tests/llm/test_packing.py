import zlib

import numpy as np
import public_tokenizers
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from subsetlab.llm.common import materialize
from subsetlab.llm.packing import FAN_IN, _passed_up, best_fit, op9_best_fit_packing, pack, pack_documents
from subsetlab.llm.word_bpe import WordBpe

PATH = public_tokenizers.path("word_bpe_49k.json")


def check(rows, capacity):
    by = {}
    for r in rows:
        by.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in by.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= capacity
    return len(by)


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(1, 32), max_size=60))
def test_best_fit(sizes):
    bins, offset, fill = best_fit(np.array(sizes, np.int64), 32)
    assert sum(fill) == sum(sizes) and all(f <= 32 for f in fill)
    assert sum(f <= 16 for f in fill) <= 1
    assert len(fill) <= max(1, -(-sum(sizes) * 11 // (9 * 32)) + 4) or not sizes


@pytest.mark.parametrize(("leaf", "factor"), [(7, 1.25), (40, 1.1), (10_000, 1.03)])
def test_tree(spark, leaf, factor):
    rng = np.random.default_rng(3)
    rows = [(i, int(x)) for i, x in enumerate(rng.integers(1, 65, 600))]
    pieces = materialize(spark, spark.createDataFrame(rows, "id long, length long"), "t")
    out = pack(spark, pieces, 64, leaf_pieces=leaf).collect()
    assert sorted((r.id, r.length) for r in out) == rows
    assert check(out, 64) <= factor * sum(x for _, x in rows) / 64 + 1


def test_sizes_are_checked(spark):
    for bad in (0, 65, None):
        with pytest.raises(ValueError):
            pack(spark, spark.createDataFrame([(bad,)], "length long"), 64)


def test_query(spark, sf):
    library = Tokenizer.from_file(PATH)
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    out = op9_best_fit_packing(spark, sf).collect()
    check(out, 2048)
    by = {}
    for r in out:
        by.setdefault(r.doc_id, []).append(r)
    assert by.keys() == texts.keys()
    for doc, rows in by.items():
        ids = np.array([*library.encode(texts[doc], add_special_tokens=False).ids, 0], "<u4")
        cut = [ids[a : a + 2048] for a in range(0, len(ids), 2048)]
        got = [(r.piece, r.start, r.length, r.ids_crc32) for r in sorted(rows, key=lambda r: r.piece)]
        assert got == [(k, k * 2048, len(c), zlib.crc32(c.tobytes())) for k, c in enumerate(cut)]


@settings(max_examples=80, deadline=None)
@given(st.lists(st.one_of(st.text(max_size=30), st.text(alphabet="abethin's 'll É1.,\n", max_size=60)), max_size=5))
def test_ids_equal_the_library(texts):
    bpe = test_ids_equal_the_library.__dict__.setdefault("bpe", WordBpe(PATH, table_entries=60))
    assert [i.tolist() for i in bpe.encode(texts)] == [bpe.library.encode(t, add_special_tokens=False).ids for t in texts]


def test_texts_of_more_stretches_than_the_table_holds():
    bpe = WordBpe(PATH, table_entries=60)
    long = " ".join(f"word{i}" for i in range(200))
    for texts in (["the cat word3 word7 sat"], [long], ["word3 word150 dog"], [long + " the cat", long]):
        assert [i.tolist() for i in bpe.encode(texts)] == [bpe.library.encode(t, add_special_tokens=False).ids for t in texts]
        assert len(bpe.hashes) <= 60


def test_cuts_at_multiples_and_very_long_texts(spark):
    library = Tokenizer.from_file(PATH)
    word = "the "
    assert len(library.encode(word * 10, add_special_tokens=False).ids) == 10
    texts = {1: word * 2047, 2: word * 2048, 3: word * 4095, 4: "ab12 " * 60_000, 5: "x" * 30_000}
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    out = pack_documents(spark, docs).collect()
    assert check(out, 2048) >= sum(r.length for r in out) / 2048
    cut = {d: [r.length for r in sorted((r for r in out if r.doc_id == d), key=lambda r: r.piece)] for d in texts}
    assert (cut[1], cut[2], cut[3]) == ([2048], [2048, 1], [2048, 2048])
    for d in (4, 5):
        ids = np.array([*library.encode(texts[d], add_special_tokens=False).ids, 0], "<u4")
        assert sum(cut[d]) == len(ids) and set(cut[d][:-1]) <= {2048}
        assert {r.ids_crc32 for r in out if r.doc_id == d} == {zlib.crc32(ids[a : a + 2048].tobytes()) for a in range(0, len(ids), 2048)}


def test_merge_nodes_stay_small(spark):
    rng = np.random.default_rng(8)
    sizes = rng.integers(1, 65, 6000)
    pieces = materialize(spark, spark.createDataFrame([(i, int(x)) for i, x in enumerate(sizes)], "id long, length long"), "t")
    out = pack(spark, pieces, 64, leaf_pieces=20).collect()  # 300 leaves, three levels
    assert check(out, 64) <= 1.2 * sizes.sum() / 64
    fill = np.array([40] * 500 + [20])
    assert _passed_up(fill, 64, 2, 0).sum() == 1 + 2 * FAN_IN


def test_nulls_and_empty_table(spark):
    docs = spark.createDataFrame([(1, None, 9), (2, "", 9), (2, "", 9)], "doc_id long, text string, length long")
    out = pack_documents(spark, docs).collect()
    assert sorted((r.doc_id, r.length) for r in out) == [(1, 1), (2, 1), (2, 1)] and check(out, 2048) == 1
    assert pack_documents(spark, docs.limit(0)).count() == 0
