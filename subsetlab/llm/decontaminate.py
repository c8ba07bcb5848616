"""Benchmark decontamination with SimHash windows.

A window has the size of the benchmark item it is compared with. Fingerprints (128-bit SimHash over 5-word shingles) are
looked up in a multi-index: with 8 blocks, two fingerprints within the radius agree in some block up to radius // 8 bits,
so trying all those neighbours of every block finds every item within the radius. Candidates are verified by exact
weighted (multiset) Jaccard similarity.

A shingle that repeats within a window or an item enters the fingerprint as several elements (first, second, ...
occurrence), each of the same weight. The weighted Jaccard of two multisets is the plain Jaccard of those elements, so
the expected distance follows from it alone: 19.4 of 128 bits at similarity 0.8, with a deviation of 4.1.

Windows whose count of benchmark shingles is too low for the similarity with any item are skipped before they are
fingerprinted; that bound is exact, so it loses nothing.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import doc_blocks, materialize, released, small_side, table, text_buffer, tidy
from .kernels import NOT_ALNUM, mix, ranges, text_shingles

WORDS = 5
SIMILARITY = 0.8
BITS, BLOCKS, RADIUS = 128, 8, 39  # 39 is 4.8 deviations above the expected distance at the similarity
SHARD_ITEMS, SHARD_BYTES = 50_000, 32 << 20  # items and bytes of text broadcast at a time; more of them take more passes
CELLS = 1 << 16  # shingles of windows with repeats that are fingerprinted together


def hash_bits(shingles: np.ndarray) -> np.ndarray:
    """(n, 128) bits of each shingle."""
    both = np.column_stack([mix(shingles), mix(shingles ^ np.uint64(0x94D049BB133111EB))])
    return np.unpackbits(both.view(np.uint8), axis=1)


def elements(shingles: np.ndarray) -> np.ndarray:
    """The shingles of every row of a matrix, in any order, with the second and later occurrences made different from the first."""
    ranked = np.sort(shingles, axis=1)
    place = np.broadcast_to(np.arange(ranked.shape[1]), ranked.shape)
    begin = np.ones(ranked.shape, bool)
    begin[:, 1:] = ranked[:, 1:] != ranked[:, :-1]
    nth = (place - np.maximum.accumulate(np.where(begin, place, 0), axis=1)).astype(np.uint64)
    return ranked ^ np.where(nth > 0, mix(nth * np.uint64(0xD1B54A32D192ED03)), np.uint64(0))


def bit_sums(windows: np.ndarray) -> np.ndarray:
    """(rows, 128) counts of ones over each row's elements."""
    rows, size = windows.shape
    step = max(1, CELLS // max(size, 1))
    return np.concatenate([hash_bits(elements(windows[i : i + step]).ravel()).reshape(-1, size, BITS).sum(axis=1, dtype=np.int32) for i in range(0, rows, step)])


def fingerprints(sums: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """(n, 8) 16-bit blocks from the counts of ones among sizes elements; a tie is a zero."""
    return np.packbits(2 * sums > sizes[:, None], axis=1).view(np.uint16)


class HammingIndex:
    """All stored fingerprints within radius of a query, by pigeonhole over blocks."""

    def __init__(self, prints: np.ndarray, radius: int = RADIUS):
        self.prints, self.radius = prints, radius
        self.order = [np.argsort(prints[:, b], kind="stable") for b in range(BLOCKS)]
        kinds = [np.unique(prints[o, b], return_index=True, return_counts=True) for b, o in enumerate(self.order)]
        self.values, self.first, self.count = ([k[i] for k in kinds] for i in range(3))
        masks = [sum(1 << i for i in c) for n in range(radius // BLOCKS + 1) for c in combinations(range(16), n)]
        self.masks = np.array(masks, np.uint16)

    def search(self, queries: np.ndarray, part: int = 512) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(query, stored, distance) for every pair within the radius; part queries at a time, to bound the neighbours in memory."""
        found = [self._search(queries[i : i + part]) for i in range(0, len(queries), part)] or [self._search(queries)]
        q, s, d = zip(*found, strict=True)
        return np.concatenate([x + i * part for i, x in enumerate(q)]), np.concatenate(s), np.concatenate(d)

    def _search(self, queries: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        n = len(self.prints)
        found = []
        for b in range(BLOCKS):
            values, back = np.unique(queries[:, b], return_inverse=True)
            own = self.values[b]
            if len(own) <= len(self.masks):  # comparing with every stored value is less work than trying all neighbours
                value, hit = np.nonzero(np.bitwise_count(values[:, None] ^ own[None, :]) <= self.radius // BLOCKS)
            else:
                near = (values[:, None] ^ self.masks[None, :]).ravel()
                hit = np.minimum(np.searchsorted(own, near), len(own) - 1)
                full = np.flatnonzero(own[hit] == near)
                value, hit = full // len(self.masks), hit[full]
            count = self.count[b][hit]
            stored = self.order[b][ranges(self.first[b][hit], count)]
            value = np.repeat(value, count)
            first, count = np.searchsorted(value, back), np.searchsorted(value, back, "right")
            count -= first
            found.append(np.repeat(np.arange(len(queries)), count) * n + stored[ranges(first, count)])
        pairs = np.unique(np.concatenate(found)) if found else np.zeros(0, np.int64)
        q, s = pairs // n, pairs % n
        distance = np.bitwise_count(queries[q] ^ self.prints[s]).sum(axis=1)
        close = distance <= self.radius
        return q[close], s[close], distance[close]


def _previous(shingles: np.ndarray) -> np.ndarray:
    """The position of the last earlier occurrence of each shingle, or -1."""
    order = np.argsort(shingles, kind="stable")
    out = np.full(len(shingles), -1, np.int64)
    same = shingles[order[1:]] == shingles[order[:-1]]
    out[order[1:][same]] = order[:-1][same]
    return out


class BenchmarkIndex:
    """Items' shingles (as multisets), sizes, fingerprints and the multi-index."""

    def __init__(self, ids: list[int], texts: list[str | None], words: int = WORDS, radius: int = RADIUS):
        raw = [(t or "").encode() for t in texts]
        offs = np.concatenate(([0], np.cumsum([len(r) for r in raw]))).astype(np.int64)
        flat, at = text_shingles(np.frombuffer(b"".join(raw), np.uint8), offs, words, NOT_ALNUM)
        full = np.flatnonzero(np.diff(at))
        self.ids, self.words = np.array(ids, np.int64)[full], words
        rows = [flat[at[i] : at[i + 1]] for i in full]
        self.items = [np.unique(r, return_counts=True) for r in rows]
        self.sizes = np.array([len(r) for r in rows], np.int64)
        self.lengths = np.unique(self.sizes)
        self.members = np.unique(flat)
        self.gate = np.zeros(1 << 22, bool)
        self.gate[(self.members >> np.uint64(42)).astype(np.int64)] = True
        sums = np.array([bit_sums(r[None, :])[0] for r in rows]).reshape(len(rows), BITS)
        self.index = HammingIndex(fingerprints(sums, self.sizes), radius)

    def member(self, shingles: np.ndarray) -> np.ndarray:
        hit = self.gate[(shingles >> np.uint64(42)).astype(np.int64)]
        some = np.flatnonzero(hit)
        at = np.minimum(np.searchsorted(self.members, shingles[some]), len(self.members) - 1)
        hit[some] = self.members[at] == shingles[some]
        return hit

    def windows(self, shingles: np.ndarray, hit: np.ndarray, least: float) -> list[tuple[int, int, int]]:
        """(start, size, item size) of a row's windows that hold enough benchmark shingles for the similarity."""
        n, sums, out = len(shingles), np.concatenate(([0], np.cumsum(hit))), []
        for size in self.lengths.tolist():
            own = min(n, size)
            need = least * (own + size) / (1 + least)
            count = sums[own:] - sums[: n - own + 1]
            out += [(s, own, size) for s in np.flatnonzero(count >= need - 1e-9).tolist()]
        return out

    def similarity(self, shingles: np.ndarray, item: int) -> float:
        keys, counts = np.unique(shingles, return_counts=True)
        mine, theirs = self.items[item]
        at = np.minimum(np.searchsorted(keys, mine), len(keys) - 1)
        both = int(np.where(keys[at] == mine, np.minimum(counts[at], theirs), 0).sum())
        return both / (len(shingles) + int(self.sizes[item]) - both)

    def best_windows(self, shingles: np.ndarray, found: list[tuple[int, int, int]], least: float) -> dict[int, tuple]:
        """item -> (-similarity, start, words, distance) of the best verified window of one row."""
        start, size, wanted = (np.array(x) for x in zip(*found, strict=True))
        low, high = int(start.min()), int((start + size).max())
        ones = np.concatenate((np.zeros((1, BITS), np.int32), np.cumsum(hash_bits(shingles[low:high]), axis=0, dtype=np.int32)))
        latest = np.maximum.accumulate(_previous(shingles))  # a window from s to e has a repeat if latest[e - 1] >= s
        best: dict[int, tuple] = {}
        for k in range(0, len(start), 4096):
            s, n = start[k : k + 4096], size[k : k + 4096]
            sums = ones[s + n - low] - ones[s - low]
            again = latest[s + n - 1] >= s
            for width in np.unique(n[again]).tolist():
                own = np.flatnonzero(again & (n == width))
                sums[own] = bit_sums(shingles[s[own][:, None] + np.arange(width)])
            prints = fingerprints(sums, n)
            for q, item, distance in zip(*(x.tolist() for x in self.index.search(prints)), strict=True):
                if self.sizes[item] != wanted[k + q]:
                    continue
                value = self.similarity(shingles[s[q] : s[q] + n[q]], item)
                if value >= least - 1e-12:
                    row = (-value, int(s[q]), int(n[q]) + self.words - 1, distance)
                    best[item] = min(best.get(item, row), row)
        return best


def scan_batch(index: BenchmarkIndex, ids: list, data: np.ndarray, offs: np.ndarray, least: float) -> list[tuple]:
    """(doc_id, item_id, start, words, similarity, distance): the best window of every document and item."""
    best: dict[tuple, tuple] = {}
    floor = least * index.lengths.min() if len(index.lengths) else math.inf  # fewer benchmark shingles never suffice
    for i, j in doc_blocks(offs):
        flat, at = text_shingles(data[offs[i] : offs[j]], offs[i : j + 1] - offs[i], index.words, NOT_ALNUM)
        hit = index.member(flat)
        total = np.concatenate(([0], np.cumsum(hit)))[at]
        for row in np.flatnonzero(np.diff(total) >= max(1, floor - 1e-9)).tolist():
            own = flat[at[row] : at[row + 1]]
            found = index.windows(own, hit[at[row] : at[row + 1]], least)
            if found:
                for item, value in index.best_windows(own, found, least).items():
                    best[i + row, item] = value
    return [(ids[o], int(index.ids[item]), s, w, -v, d) for (o, item), (v, s, w, d) in sorted(best.items())]


@tidy
def contaminated(spark: SparkSession, docs: DataFrame, benchmark: DataFrame, least: float = SIMILARITY, words: int = WORDS, radius: int = RADIUS, shard_items: int = SHARD_ITEMS, shard_bytes: int = SHARD_BYTES) -> DataFrame:
    """doc_id, item_id, start_word, n_words, similarity, distance: documents that hold a benchmark item, best window each.

    Words are lower-cased runs of ASCII letters, digits and other scripts' characters, so punctuation does not matter. A document shorter
    than an item is one window. Texts and items without words (null, empty) and rows without item_id match nothing;
    items of fewer than five words match only documents that are that sequence. Repeated rows are answered one by one.
    Extra columns are ignored; an empty table on either side gives no rows.

    A benchmark of over shard_items items or shard_bytes bytes goes in shards of that size: the documents are scanned
    once for each, and a shard's index is released before the next one is built.
    """
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), "text").filter("item_id IS NOT NULL")
    n, size = items.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()
    shards = max(1, -(-n // shard_items), -(-size // shard_bytes))
    if shards == 1:
        return _scan(spark, docs, items, least, words, radius)[0]
    out = None
    for shard in range(shards):
        found, index = _scan(spark, docs, items.filter(F.pmod(F.xxhash64("item_id"), F.lit(shards)) == shard), least, words, radius)
        found = materialize(spark, found, "contaminated-shard")
        index.destroy()
        out = found if out is None else out.unionByName(found)
    return out


def _scan(spark: SparkSession, docs: DataFrame, items: DataFrame, least: float, words: int, radius: int):
    """The rows of one shard, lazily, and the broadcast index that they need."""
    part = items.toArrow()
    index = spark.sparkContext.broadcast(BenchmarkIndex(part.column(0).to_pylist(), part.column(1).to_pylist(), words, radius))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["doc_id", "item_id", "start_word", "n_words", "similarity", "distance"]
        kinds = [pa.int64()] * 4 + [pa.float64(), pa.int32()]
        for batch in released(batches):
            if len(index.value.ids):
                rows = scan_batch(index.value, batch.column(0).to_pylist(), *text_buffer(batch.column(1)), least)
                cols = list(zip(*rows, strict=True)) or [()] * 6
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names)

    schema = "doc_id long, item_id long, start_word long, n_words long, similarity double, distance int"
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, schema), index


@tidy
def drop_contaminated(spark: SparkSession, docs: DataFrame, benchmark: DataFrame, least: float = SIMILARITY) -> DataFrame:
    """docs without the documents that hold a benchmark item; columns unchanged.

    Rows that share a doc_id are one document: all of them go if one holds an item. Rows without doc_id stay.
    """
    bad = materialize(spark, contaminated(spark, docs, benchmark, least).select("doc_id").distinct(), "contaminated")
    return docs.join(small_side(bad), "doc_id", "left_anti").select(*docs.columns)


def op7_simhash_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contaminated(spark, table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
