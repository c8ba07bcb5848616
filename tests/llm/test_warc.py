import base64
import gzip
import hashlib
import io
import json
import zlib

import pytest
from pyarrow import fs

from subsetlab.llm.common import new_path
from subsetlab.llm.warc import archive_round_trip, normalise_stream, op2_warc_normaliser, record_head


def expected(pages, at_least=0):
    by = {}
    for p, h in pages:
        if len((h or "").encode()) >= at_least:
            by.setdefault(h or "", []).append(p)
    out = []
    for p, h in pages:
        raw = (h or "").encode()
        top = max(by.get(h or "", [p]))
        out.append((p, len(raw), base64.b32encode(hashlib.sha1(raw).digest()).decode(), "response" if p == top else "revisit", None if p == top else top))
    return sorted(out)


def test_query(spark, sf):
    pages = [(r.page_id, r.html) for r in spark.read.parquet(f"{sf}/pages.parquet").collect()]
    assert sorted(tuple(r) for r in op2_warc_normaliser(spark, sf).collect()) == expected(pages)


@pytest.mark.parametrize("at_least", [0, 5])
def test_copies_nulls_and_files(spark, at_least):
    html = ["<p>é</p>" * 3, None, "", "<p>é</p>" * 3, "x\r\n\r\nWARC/1.1\r\n", "y" * 700_000, "<p>é</p>" * 3, "abc", "abc"]
    rows = [(i, None if i == 2 else f"http://h/{i}\r\nX: y", h, 0) for i, h in enumerate(html)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, length long")
    folder = new_path(spark, "t")
    got = archive_round_trip(spark, df, folder, at_least, payloads=True).collect()
    assert sorted((r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) for r in got) == expected([(i, h) for i, _, h, _ in rows], at_least)
    for r in got:
        assert r.payload == (None if r.record_type == "revisit" else (html[r.page_id] or "").encode())
    store, root = fs.FileSystem.from_uri(folder)
    seen = 0
    for f in store.get_file_info(fs.FileSelector(root)):
        if f.path.endswith(".idx"):
            raw = store.open_input_file(f.path.removesuffix(".idx")).read()
            entries = [json.loads(x) for x in store.open_input_file(f.path).read().splitlines()]
            assert sum(e["length"] for e in entries) == len(raw)
            for e in entries:
                assert gzip.decompress(raw[e["offset"] : e["offset"] + e["length"]]).startswith(b"WARC/1.1\r\n")
            seen += len(entries)
    assert seen == len(html)
    assert archive_round_trip(spark, df.limit(0)).count() == 0


def test_repeated_and_null_ids(spark):
    df = spark.createDataFrame([(1, "u", "a"), (1, "u", "a"), (None, "u", "a"), (None, None, "b")], "page_id long, url string, html string")
    got = sorted((r.page_id or -1, r.record_type, r.refers_to) for r in archive_round_trip(spark, df).collect())
    assert got == sorted([(1, "response", None), (1, "response", None), (-1, "revisit", 1), (-1, "response", None)], key=lambda x: (x[0], x[1]))


def test_stream_of_members_and_broken_streams():
    blocks = [record_head(i, "http://h/", p, None) + p + b"\r\n\r\n" for i, p in enumerate((b"", b"abc", b"z" * 900_000))]
    for whole in (gzip.compress(b"".join(blocks)), b"".join(map(gzip.compress, blocks))):
        sink = io.BytesIO()
        entries = list(normalise_stream(io.BytesIO(whole), sink))
        assert [zlib.decompress(sink.getvalue()[e["offset"] : e["offset"] + e["length"]], 31) for e in entries] == blocks
    with pytest.raises(ValueError):
        list(normalise_stream(io.BytesIO(gzip.compress(blocks[2][:-400])), io.BytesIO()))
