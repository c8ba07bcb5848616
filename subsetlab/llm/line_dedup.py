"""Line dedup across documents with a sharded minimal perfect hash.

1. Every text is cut into lines; a line's key (stripped, A-Z lower-cased) is kept as a 128-bit hash.
2. Keys are counted by distinct document (map-side combined); keys of one document need no entry.
3. Repeated keys go to shards by hash. A shard builds a minimal perfect hash with fingerprint, count and owner arrays
   and the documents' keys of that shard probe those arrays; only the lines that lose come out.
   Keys that many documents hold are few (their number is bounded by lines / HOT_SHARE): they form one extra shard
   that is broadcast and probed where the documents are, so no shard receives a hot line's occurrences.
4. The losing line numbers meet the texts once, by document.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import doc_blocks, materialize, released, table, text_buffer
from .kernels import LOWER, SECOND, SPACE, span_hashes
from .mphf import LineIndex

MIN_CHARS = 10
HOT_SHARE = 20_000  # a key is hot when over 1/HOT_SHARE of all key occurrences are its own


def line_spans(data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the lines (cut at LF, without it) and each row's first line; an empty row has one line."""
    feeds = np.flatnonzero(data == 10)
    row_feeds = np.searchsorted(feeds, offs)
    n_lines = np.diff(row_feeds) + 1
    first = np.concatenate(([0], np.cumsum(n_lines)))
    starts, ends = np.empty(first[-1], np.int64), np.empty(first[-1], np.int64)
    head, tail = np.zeros(first[-1], bool), np.zeros(first[-1], bool)
    head[first[:-1]] = tail[first[1:] - 1] = True
    starts[head], starts[~head] = offs[:-1], feeds + 1
    ends[tail], ends[~tail] = offs[1:], feeds
    return starts, ends, first


def line_keys(data: np.ndarray, offs: np.ndarray, min_chars: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Row, line number and two hashes of every line whose key has at least min_chars code points."""
    starts, ends, first = line_spans(data, offs)
    ink = np.flatnonzero(~SPACE[data])
    lo, hi = np.searchsorted(ink, starts), np.searchsorted(ink, ends)
    full = np.flatnonzero(lo < hi)
    begin, stop = ink[lo[full]], ink[hi[full] - 1] + 1
    chars = np.concatenate(([0], np.cumsum((data & 0xC0) != 0x80)))
    long = chars[stop] - chars[begin] >= min_chars
    full, begin, stop = full[long], begin[long], stop[long]
    row = np.searchsorted(first, full, "right") - 1
    low = LOWER[data]
    return row, full - first[row], span_hashes(low, begin, stop), span_hashes(low, begin, stop, SECOND)


def _keys_of_batches(batches: Iterator[pa.RecordBatch], min_chars: int, distinct: bool) -> Iterator[pa.RecordBatch]:
    for batch in released(batches):
        ids = np.asarray(batch.column(0).to_numpy(zero_copy_only=False), np.int64)
        data, offs = text_buffer(batch.column(1))
        for i, j in doc_blocks(offs):
            row, line, h1, h2 = line_keys(data[offs[i] : offs[j]], offs[i : j + 1] - offs[i], min_chars)
            if not len(row):
                continue
            doc = ids[i:j][row]
            if distinct:
                order = np.lexsort((h2, h1, doc))
                d, a, b = doc[order], h1[order], h2[order]
                new = np.concatenate(([True], (d[1:] != d[:-1]) | (a[1:] != a[:-1]) | (b[1:] != b[:-1])))
                yield pa.RecordBatch.from_arrays([pa.array(d[new]), pa.array(a[new].view(np.int64)), pa.array(b[new].view(np.int64))], ["doc_id", "h1", "h2"])
            else:
                yield pa.RecordBatch.from_arrays([pa.array(doc), pa.array(line), pa.array(h1.view(np.int64)), pa.array(h2.view(np.int64))], ["doc_id", "line", "h1", "h2"])


def repeated_keys(docs: DataFrame, min_chars: int = MIN_CHARS) -> DataFrame:
    """(h1, h2, n, owner, last): keys with the documents that hold them; n counts a document once."""
    keys = docs.select("doc_id", "text").mapInArrow(lambda it: _keys_of_batches(it, min_chars, True), "doc_id long, h1 long, h2 long")
    return keys.groupBy("h1", "h2").agg(F.count(F.lit(1)).alias("n"), F.min("doc_id").alias("owner"), F.max("doc_id").alias("last"))


def _index_of(keys: dict[str, np.ndarray]) -> LineIndex:
    return LineIndex(keys["h1"].view(np.uint64), keys["h2"].view(np.uint64), keys["n"], keys["owner"])


def _probe_shards(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by (shard, kind, ...): a shard's index rows (kind 0) come before the probes (kind 1)."""
    shard, parts, index = None, [], None
    for batch in released(batches):
        c = {n: batch.column(k).to_numpy(zero_copy_only=False) for k, n in enumerate(batch.schema.names)}
        cuts = np.concatenate(([0], np.flatnonzero(np.diff(c["shard"]) | np.diff(c["kind"])) + 1, [len(c["shard"])]))
        for i, j in zip(cuts[:-1], cuts[1:], strict=True):
            if c["shard"][i] != shard:
                shard, parts, index = c["shard"][i], [], None
            piece = {n: v[i:j] for n, v in c.items()}
            if piece["kind"][0] == 0:
                parts.append(piece)
                continue
            if index is None and parts:
                index, parts = _index_of({n: np.concatenate([p[n] for p in parts]) for n in ("h1", "h2", "n", "owner")}), []
            if index is None:
                continue  # no repeated key in this shard
            count, owner = index.probe(piece["h1"].view(np.uint64), piece["h2"].view(np.uint64))
            lose = (count > 0) & (owner != piece["owner"])
            if lose.any():
                yield pa.RecordBatch.from_arrays([pa.array(piece["owner"][lose]), pa.array(piece["line"][lose])], ["doc_id", "line"])


def losing_lines(spark: SparkSession, docs: DataFrame, min_chars: int = MIN_CHARS, shards: int | None = None, hot_share: int = HOT_SHARE) -> DataFrame:
    """(doc_id, line): lines that another document of smaller doc_id holds too. Rows without doc_id take no part."""
    docs = docs.select("doc_id", "text").filter("doc_id IS NOT NULL")
    keys = materialize(spark, repeated_keys(docs, min_chars).filter("owner < last").drop("last"), "line-keys")
    total = keys.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.count(F.lit(1)).alias("k")).first()
    bound = max(100, total["n"] // hot_share)
    shards = shards or max(4 * int(spark.conf.get("spark.sql.shuffle.partitions")), total["k"] // 500_000)
    hot = keys.filter(F.col("n") > bound).select("h1", "h2", "n", "owner").toArrow()  # at most hot_share rows
    hot = spark.sparkContext.broadcast({n: hot.column(n).to_numpy() for n in hot.column_names})
    lines = docs.mapInArrow(lambda it: _keys_of_batches(it, min_chars, False), "doc_id long, line long, h1 long, h2 long")

    def probe_hot(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Answers hot keys here (lost: true or false) and leaves the others to their shard (lost: null)."""
        index = _index_of(hot.value)
        for batch in released(batches):
            h1, h2 = batch.column(2).to_numpy().view(np.uint64), batch.column(3).to_numpy().view(np.uint64)
            count, owner = index.probe(h1, h2)
            lost = pa.array(owner != batch.column(0).to_numpy(), mask=count == 0)
            keep = pa.array((count == 0) | (owner != batch.column(0).to_numpy()))
            yield pa.RecordBatch.from_arrays([*batch.columns, lost], ["doc_id", "line", "h1", "h2", "lost"]).filter(keep)

    seen = lines.mapInArrow(probe_hot, "doc_id long, line long, h1 long, h2 long, lost boolean")
    shard = F.pmod(F.col("h1"), F.lit(shards)).cast("long").alias("shard")
    index_rows = keys.filter(F.col("n") <= bound).select(shard, F.lit(0).alias("kind"), "h1", "h2", "n", "owner", F.lit(0).cast("long").alias("line"))
    # Hot losers ride along under pseudo-shards of their own, dealt evenly, as kind 2.
    probes = seen.select(
        F.when(F.col("lost").isNull(), F.pmod("h1", F.lit(shards))).otherwise(F.lit(-1) - F.pmod(F.xxhash64("doc_id"), F.lit(shards))).cast("long").alias("shard"),
        F.when(F.col("lost").isNull(), 1).otherwise(2).alias("kind"), "h1", "h2", F.lit(0).cast("long").alias("n"), F.col("doc_id").alias("owner"), "line",
    )

    def answer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rest(it):
            for b in it:
                hot_rows = b.filter(pa.array(b.column(1).to_numpy() == 2))
                if hot_rows.num_rows:
                    ready.append(pa.RecordBatch.from_arrays([hot_rows.column(5), hot_rows.column(6)], ["doc_id", "line"]))
                yield b.filter(pa.array(b.column(1).to_numpy() != 2))

        ready: list[pa.RecordBatch] = []
        for out in _probe_shards(b for b in rest(batches) if b.num_rows):
            yield out
            while ready:
                yield ready.pop()
        yield from ready

    both = index_rows.unionByName(probes).repartition("shard").sortWithinPartitions("shard", "kind")
    return both.mapInArrow(answer, "doc_id long, line long")


def _rewrite(batches: Iterator[pa.RecordBatch], with_text: bool) -> Iterator[pa.RecordBatch]:
    for batch in released(batches):
        ids, texts, drops = batch.column(0), batch.column(1), batch.column(2)
        n_lines, n_dropped, digest, kept = [], [], [], []
        for text, drop in zip(texts, drops, strict=True):
            raw = text.as_buffer().to_pybytes() if text.is_valid else b""
            lost = set(drop.as_py()) if drop.is_valid else ()
            total = raw.count(b"\n") + 1
            if lost:
                raw = b"\n".join(x for i, x in enumerate(raw.split(b"\n")) if i not in lost)
            n_lines.append(total)
            n_dropped.append(len(lost))
            digest.append(hashlib.sha256(raw).hexdigest())
            kept.append(raw.decode("utf-8") if with_text else None)
        arrays = [ids, pa.array(n_lines, pa.int64()), pa.array(n_dropped, pa.int64()), pa.array(digest)]
        names = ["doc_id", "n_lines", "n_dropped", "kept_sha256"]
        yield pa.RecordBatch.from_arrays(arrays + [pa.array(kept, pa.string())] * with_text, names + ["kept_text"] * with_text)


def line_dedup(spark: SparkSession, docs: DataFrame, min_chars: int = MIN_CHARS, with_text: bool = False, shards: int | None = None, hot_share: int = HOT_SHARE) -> DataFrame:
    """doc_id, n_lines, n_dropped, kept_sha256 (and kept_text): a line whose key has at least min_chars code points stays only in the smallest doc_id that holds it.

    Null or empty text is one empty line. Repeats inside the owning document stay. Rows that share a doc_id count as one
    document, and every one of them loses the lines that any of them loses at that line number. Rows without doc_id are
    returned untouched. Extra columns are ignored.
    """
    lost = losing_lines(spark, docs, min_chars, shards, hot_share).groupBy("doc_id").agg(F.collect_set("line").alias("lost"))
    lost = materialize(spark, lost, "lost-lines")  # a document's own line numbers: bounded by its length
    joined = docs.select("doc_id", "text").join(lost.hint("merge"), "doc_id", "left").select("doc_id", "text", "lost")
    return joined.mapInArrow(lambda it: _rewrite(it, with_text), "doc_id long, n_lines long, n_dropped long, kept_sha256 string" + ", kept_text string" * with_text)


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup(spark, table(spark, sf_dir, "documents"))


OP10_SQL = r"""
WITH d AS (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS ls FROM documents),
l AS (SELECT doc_id, unnest(ls) AS line, unnest(range(1, len(ls) + 1)) AS pos FROM d),
k AS (SELECT *, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
      'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
g AS (SELECT key, min(doc_id) AS owner FROM k WHERE length(key) >= 10 GROUP BY key HAVING count(DISTINCT doc_id) >= 2),
m AS (SELECT k.doc_id, k.line, k.pos, g.owner IS NOT NULL AND g.owner <> k.doc_id AS lose FROM k LEFT JOIN g ON g.key = k.key)
SELECT doc_id, CAST(count(*) AS BIGINT) AS n_lines, CAST(count(*) FILTER (WHERE lose) AS BIGINT) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT lose), '')) AS kept_sha256
FROM m GROUP BY doc_id
"""
