import numpy as np
import pyarrow as pa
import pytest

from subsetlab.llm.common import cleanup, doc_blocks, materialize, text_buffer
from subsetlab.llm.kernels import shingle_hashes, span_hashes, text_shingles, word_spans


def buffer(texts):
    return text_buffer(pa.array(texts, pa.string()))


def test_buffers_of_slices_and_nulls():
    data, offs = text_buffer(pa.array(["ab", None, "", "é"], pa.large_string()).slice(1))
    assert data.tobytes().decode() == "é" and offs.tolist() == [0, 0, 0, 2]
    assert text_buffer(pa.array([], pa.string()))[1].tolist() == [0]
    assert [b for b in doc_blocks(np.array([0, 5, 6, 7, 30]), 4)] == [(0, 1), (1, 3), (3, 4)]


def test_words_stop_at_rows():
    data, offs = buffer(["ab cd", "", "ef", " \t", "g\x0bh"])
    starts, ends, first = word_spans(data, offs)
    assert [data[a:b].tobytes().decode() for a, b in zip(starts, ends, strict=True)] == ["ab", "cd", "ef", "g", "h"]
    assert first.tolist() == [0, 2, 2, 3, 3, 5]


def test_hashes_depend_on_content_only():
    data, offs = buffer(["abc xyz abc", "abc"])
    starts, ends, _ = word_spans(data, offs)
    h = span_hashes(data, starts, ends)
    assert h[0] == h[2] == h[3] != h[1]
    words = [f"{a}{b}{c}" for a in "abcdefghij" for b in "klmnopqrst" for c in "uvwxyz\x01\x02"]
    data, offs = buffer([" ".join(words)])
    assert len(set(span_hashes(data, *word_spans(data, offs)[:2]).tolist())) == len(words)


def test_shingles_of_short_rows():
    flat, at = text_shingles(*buffer(["a b c d", "a b", "A  B", "", "b"]), 3)
    assert np.diff(at).tolist() == [2, 1, 1, 0, 1]
    assert flat[at[1]] == flat[at[2]] != flat[at[4]]
    assert shingle_hashes(np.zeros(0, np.uint64), np.array([0, 0]), 3)[1].tolist() == [0, 0]


def test_tables_and_cleanup(spark):
    made = materialize(spark, spark.range(5), "t")
    assert made.count() == 5
    cleanup(spark)
    with pytest.raises(Exception):
        materialize(spark, made, "again").count()
