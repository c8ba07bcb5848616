import random

import public_tokenizers
import pytest
import sentencepiece
from hypothesis import given, settings
from hypothesis import strategies as st

from subsetlab.llm.token_count import PrefixCounter, op4_token_count, token_counts

MODEL = public_tokenizers.path("piece_bpe_32k.model")


@pytest.fixture(scope="module")
def both():
    return PrefixCounter(MODEL, cache_entries=50), sentencepiece.SentencePieceProcessor(model_file=MODEL)


@settings(max_examples=150, deadline=None)
@given(st.one_of(st.text(max_size=40), st.text(alphabet=" \nabcdethinong.,é▁0", max_size=60)))
def test_every_prefix_equals_the_library(both, text):
    own, library = both
    counts = own.prefix_counts(text)
    assert counts.tolist() == [len(library.encode(text[:i])) for i in range(len(text) + 1)]
    assert own.count(text) == counts[-1]


def test_pieces_stay_apart_exactly_when_merging_leaves_them(both):
    own, rng = both[0], random.Random(3)
    pieces = sorted(own.score)
    pairs = [(rng.choice(pieces), rng.choice(pieces)) for _ in range(4000)]
    cut = [(p[:i], p[i:]) for p in rng.sample(pieces, 2000) for i in range(1, len(p)) if p[:i] in own.score and p[i:] in own.score]
    pairs += cut + [("a", "aa"), ("aa", "a"), ("aa", "aa"), ("é", "漢"), ("漢", "字")]
    seen = {own._no_merge_across(a, b) for a, b in pairs if a in own.score and b in own.score}
    assert seen == {True, False}
    assert all(own._no_merge_across(a, b) == (own.merged(a + b) == [a, b]) for a, b in pairs)


def test_very_long_texts(both):
    own, library = both
    for text in ("ab" * 60_000, "word " * 40_000, "\n" * 30_000, "漢" * 20_000 + "𐍈" * 20_000):
        assert own.count(text) == len(library.encode(text))
    assert all(len(k) <= 64 for k in own.totals)


def test_budget(both):
    own, library = both
    text = "the quick brown fox jumps over the lazy dog\n" * 3
    at = own.fitting(text, 10)
    assert len(library.encode(text[:at])) <= 10 < len(library.encode(text[: at + 1]))
    assert own.fitting("", 5) == 0


def test_query(spark, sf):
    library = sentencepiece.SentencePieceProcessor(model_file=MODEL)
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    rows = op4_token_count(spark, sf).collect()
    assert len(rows) == len(texts)
    for r in rows:
        n = len(library.encode(texts[r.doc_id]))
        assert (r.n_bytes, r.n_tokens, r.over_limit) == (len(texts[r.doc_id].encode()), n, n > 4096)


def test_nulls_and_clashing_columns(spark):
    docs = spark.createDataFrame([(1, None, 5), (1, "", 6), (None, "a b", 7)], "doc_id long, text string, n_tokens long")
    rows = sorted(token_counts(docs, prefixes=True).collect(), key=repr)
    assert sorted((r.doc_id is None, r.n_tokens, r.prefix_counts) for r in rows) == [(False, 0, [0]), (False, 0, [0]), (True, 2, [0, 1, 2, 2])]
    assert token_counts(docs.limit(0)).count() == 0
