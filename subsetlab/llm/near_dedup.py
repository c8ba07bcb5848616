"""Near dedup by MinHash with tensored banding.

Two collections of m bundles of t min-hashes each are computed per document: 2 * m * t hashes. A table key pairs a bundle
of the first with one of the second, so there are m * m tables of 2 * t rows each; banding without pairing would need
2 * m * m * t hashes. A pair of similarity s shares a table with probability (1 - (1 - s**t)**m)**2.

Equal shingle sets form classes first, so copies cost one representative. Every table bucket is then searched as a star
around the member that shares most buckets overall, links are confirmed on full sets, and components are formed. Where
a bucket still holds several components, the pairs across its components are confirmed too, each in the first table where
it meets. Sets are cut by hash into BINS parts for that: the smaller counts of each part add up to an upper bound of the
intersection, so a pair below the similarity by that bound needs no full sets. Pairs inside a component are never formed.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import doc_blocks, materialize, released, small_side, table, text_buffer, tidy
from .graph import components
from .kernels import MinHasher, mix, text_shingles

BUNDLES = 14  # m
ROWS = 4  # t
BINS = 128  # parts of a set in its sketch
BLOCK = 2_000  # members of a bucket compared in one go; larger buckets are dealt out as pairs of blocks


def distinct_sets(data: np.ndarray, offs: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of every row, one after the other, and row boundaries."""
    flat, at = text_shingles(data, offs, k)
    keep = np.ones(len(flat), bool)
    for i, j in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
        if j - i > 1:
            part = flat[i:j]
            part.sort()
            np.not_equal(part[1:], part[:-1], out=keep[i + 1 : j])
    return flat[keep], np.concatenate(([0], np.cumsum(keep)))[at]


def signatures(docs: DataFrame, k: int, bundles: int = BUNDLES, rows: int = ROWS) -> DataFrame:
    """doc_id, n (set size), s1, s2 (set fingerprint), ga, gb (the two collections' bundles; null for an empty set)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher = MinHasher(2 * bundles * rows)
        for batch in released(batches):
            data, offs = text_buffer(batch.column(1))
            for i, j in doc_blocks(offs):
                flat, at = distinct_sets(data[offs[i] : offs[j]], offs[i : j + 1] - offs[i], k)
                n = np.diff(at)
                full = np.flatnonzero(n)
                s1, s2 = np.zeros(len(n), np.uint64), np.zeros(len(n), np.uint64)
                bundle = np.zeros((len(n), 2 * bundles), np.uint64)
                if len(full):
                    begin = at[:-1][full]
                    s1[full] = np.add.reduceat(mix(flat + np.uint64(1)), begin)
                    s2[full] = np.bitwise_xor.reduceat(mix(flat ^ np.uint64(0x5DEECE66D)), begin)
                    sig = hasher(flat, np.append(begin, len(flat))).reshape(len(full), 2 * bundles, rows)
                    h = np.zeros((len(full), 2 * bundles), np.uint64)
                    for c in range(rows):
                        h = mix(h * np.uint64(0xA24BAED4963EE407) + sig[:, :, c])
                    bundle[full] = h
                null = n == 0
                lists = [pa.FixedSizeListArray.from_arrays(pa.array(b.ravel().view(np.int64)), bundles).cast(pa.list_(pa.int64())) for b in (np.ascontiguousarray(bundle[:, :bundles]), np.ascontiguousarray(bundle[:, bundles:]))]
                lists = [pa.ListArray.from_arrays(pa.array(np.arange(len(n) + 1, dtype=np.int32) * bundles), x.values, mask=pa.array(null)) for x in lists]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), pa.array(n, pa.int64()), pa.array(s1.view(np.int64)), pa.array(s2.view(np.int64)), *lists], ["doc_id", "n", "s1", "s2", "ga", "gb"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, n long, s1 long, s2 long, ga array<long>, gb array<long>")


def shingle_sets(docs: DataFrame, k: int) -> DataFrame:
    """id, hashes: the sorted distinct 64-bit shingle hashes of a text as bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in released(batches):
            data, offs = text_buffer(batch.column(1))
            for i, j in doc_blocks(offs):
                flat, at = distinct_sets(data[offs[i] : offs[j]], offs[i : j + 1] - offs[i], k)
                sets = [flat[a:b].tobytes() for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), pa.array(sets, pa.binary())], ["id", "hashes"])

    return docs.select(F.col("doc_id").alias("id"), "text").mapInArrow(run, "id long, hashes binary")


def intersections(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """a, b, both: the size of the intersection of two full sets."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in released(batches):
            out = []
            for x, y in zip(batch.column(2), batch.column(3), strict=True):
                x, y = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                if len(x) > len(y):
                    x, y = y, x
                at = np.searchsorted(y, x)
                at[at == len(y)] = 0
                out.append(int(np.count_nonzero(y[at] == x)) if len(y) else 0)
            yield pa.RecordBatch.from_arrays([*batch.columns[:2], pa.array(out, pa.int64())], ["a", "b", "both"])

    first = sets.select(F.col("id").alias("a"), F.col("hashes").alias("x")).hint("merge")
    second = sets.select(F.col("id").alias("b"), F.col("hashes").alias("y")).hint("merge")
    return pairs.select("a", "b").join(first, "a").join(second, "b").select("a", "b", "x", "y").mapInArrow(run, "a long, b long, both long")


def sketches(sets: DataFrame) -> DataFrame:
    """id, sketch: how many of a set's hashes fall into each of BINS parts, a byte each; 255 stands for any larger count."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in released(batches):
            counts = [np.bincount((np.frombuffer(x.as_buffer(), np.uint64) >> np.uint64(57)).astype(np.int64), minlength=BINS) for x in batch.column(1)]
            out = [np.minimum(c, 255).astype(np.uint8).tobytes() for c in counts]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.binary())], ["id", "sketch"])

    return sets.mapInArrow(run, "id long, sketch binary")


class _Members:
    """Members of a bucket in order of set size; table is the bucket's pair of bundles (i, j)."""

    def __init__(self, held: list[pa.RecordBatch], table_bits: int):
        t = pa.Table.from_batches(held)
        n = t["n"].to_numpy()
        order = np.argsort(n, kind="stable")
        self.id, self.n, self.comp, self.block = (t[c].to_numpy()[order] for c in ("id", "n", "comp", "u"))
        self.sketch = np.frombuffer(b"".join(t["sketch"].to_pylist()), np.uint8).reshape(-1, BINS)[order]
        self.full = (self.sketch == 255).any(axis=1)
        self.ga, self.gb = (t[c].combine_chunks().flatten().to_numpy().reshape(len(n), -1)[order] for c in ("ga", "gb"))
        self.table = divmod(int(t["key"][0].as_py()) & (1 << table_bits) - 1, self.ga.shape[1])

    def first_here(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """Pairs that agree in no earlier bundle of either collection, so in no earlier table."""
        out = np.ones(len(x), bool)
        for codes, upto in zip((self.ga, self.gb), self.table, strict=True):
            for c in range(upto):
                out &= codes[x, c] != codes[y, c]
        return out

    def possible(self, percent: int, part: int = 1 << 16) -> tuple[np.ndarray, np.ndarray]:
        """The pairs across components, and across blocks where there are two, that are new here and that sizes and sketches allow to be similar."""
        size, two = self.n, len(np.unique(self.block)) > 1
        high = np.searchsorted(size, size * 100 // percent, "right")  # larger sets share too little with this one
        step = max(1, part // len(size))
        first, second = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for lo in range(0, len(size), step):
            rows, top = np.arange(lo, min(lo + step, len(size))), int(high[min(lo + step, len(size)) - 1])
            cols = np.arange(lo, top)
            go = (cols > rows[:, None]) & (cols < high[rows][:, None]) & (self.comp[rows][:, None] != self.comp[cols])
            if two:
                go &= self.block[rows][:, None] != self.block[cols]
            x, y = np.nonzero(go)
            x, y = rows[x], cols[y]
            new = self.first_here(x, y)
            x, y = x[new], y[new]
            both = np.minimum(self.sketch[x], self.sketch[y]).sum(axis=1, dtype=np.int64)
            both = np.where(self.full[x] | self.full[y], np.minimum(size[x], size[y]), both)
            fit = 100 * both >= percent * (size[x] + size[y] - both)
            first.append(x[fit])
            second.append(y[fit])
        return np.concatenate(first), np.concatenate(second)


def across_components(members: DataFrame, percent: int, table_bits: int, block: int = BLOCK) -> DataFrame:
    """a, b, n, m: the pairs of a bucket's members (key, c, id, n, comp, sketch, ga, gb) in different components that may be similar; a pair comes from one bucket only."""
    cells = F.ceil(F.col("c") / block).cast("int")
    dealt = members.withColumn("u", F.pmod(F.xxhash64("id"), cells).cast("int")).withColumn("v", F.explode(F.sequence(F.lit(0), cells - 1)))
    dealt = dealt.select("key", F.least("u", "v").alias("p"), F.greatest("u", "v").alias("q"), "id", "n", "comp", "u", "sketch", "ga", "gb")

    def pairs(held: list[pa.RecordBatch]) -> pa.RecordBatch:
        m = _Members(held, table_bits)
        x, y = m.possible(percent)
        swap = m.id[x] > m.id[y]
        x, y = np.where(swap, y, x), np.where(swap, x, y)
        return pa.RecordBatch.from_arrays([pa.array(c) for c in (m.id[x], m.id[y], m.n[x], m.n[y])], ["a", "b", "n", "m"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, last = [], None  # the cell at the end of a batch may go on in the next
        for batch in released(batches):
            if not batch.num_rows:
                continue
            cell = np.column_stack([batch.column(c).to_numpy() for c in range(3)])
            edges = [0, *(np.flatnonzero((cell[1:] != cell[:-1]).any(axis=1)) + 1).tolist(), len(cell)]
            for i, j in zip(edges[:-1], edges[1:], strict=True):
                if held and tuple(cell[i]) != last:
                    yield pairs(held)
                    held = []
                held.append(batch.slice(i, j - i))
                last = tuple(cell[i])
        if held:
            yield pairs(held)

    return dealt.repartition("key", "p", "q").sortWithinPartitions("key", "p", "q").mapInArrow(run, "a long, b long, n long, m long")


def _similar(both, n, m, percent: int):
    """100 * |intersection| >= percent * |union|."""
    return (both > 0) & (100 * both >= percent * (n + m - both))


def _fits(n, m, percent: int):
    """A pair's sizes allow the similarity."""
    return 100 * F.least(n, m) >= percent * F.greatest(n, m)


@tidy
def near_components(spark: SparkSession, docs: DataFrame, k: int = 5, percent: int = 80, bundles: int = BUNDLES, rows: int = ROWS) -> DataFrame:
    """One row per input row: doc_id, n_shingles, component_id, kept.

    Words are lower-cased (A-Z) runs of other bytes than blanks; a set holds the distinct k-word shingles, or the whole
    sequence as one where there are fewer words. Texts without words (null, empty, blank) have an empty set and link to
    nothing. Documents link when 100 * |intersection| >= percent * |union|; component_id is the smallest doc_id that a
    document reaches. Rows that share a doc_id are one document with several texts. A null doc_id gets a null
    component_id and is kept. Extra columns are ignored; an empty table gives no rows.
    """
    base = materialize(spark, signatures(docs, k, bundles, rows), "signatures")
    named = base.filter("doc_id IS NOT NULL AND n > 0")
    # As a table, so that joins by set read plain exchanges, which Spark splits where a set is very frequent.
    classes = materialize(spark, named.groupBy("s1", "s2", "n").agg(F.min("doc_id").alias("rep")), "classes")
    reps = named.join(classes.withColumnRenamed("rep", "doc_id").hint("merge"), ["doc_id", "s1", "s2", "n"], "left_semi").select(F.col("doc_id").alias("id"), "n", "ga", "gb")
    # A pair must agree on a bundle of the first collection at least: the other documents need no table keys.
    codes = reps.select("id", F.posexplode("ga").alias("i", "a"))
    shared = codes.groupBy("i", "a").agg(F.count(F.lit(1)).alias("c")).filter("c > 1").hint("merge")
    able = codes.join(shared, ["i", "a"], "left_semi").select("id").distinct().hint("merge")
    keyed = reps.join(able, "id", "left_semi").select("id", "n", "gb", F.posexplode("ga").alias("i", "a")).select("id", "n", "i", "a", F.posexplode("gb").alias("j", "b"))
    bits = (bundles * bundles - 1).bit_length()  # a key ends in its table's number
    key = F.shiftleft(F.xxhash64("i", "j", "a", "b"), bits) + F.col("i") * bundles + F.col("j")
    keyed = materialize(spark, keyed.select(key.alias("key"), "id", "n"), "table-keys")
    buckets = keyed.groupBy("key").agg(F.count(F.lit(1)).alias("c")).filter("c > 1").hint("merge")
    members = materialize(spark, keyed.join(buckets, "key"), "buckets")
    ids = members.select("id").distinct()
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(small_side(ids.withColumnRenamed("id", "doc_id")), "doc_id", "left_semi")
    sets = materialize(spark, shingle_sets(texts, k), "sets")
    degree = members.groupBy("id").agg(F.sum("c").alias("degree")).hint("merge")
    top = members.join(degree, "id").groupBy("key").agg(F.max(F.struct("degree", -F.col("id"), "n")).alias("top"))
    leaders = materialize(spark, top.select("key", (-F.col("top.col2")).alias("lead"), F.col("top.n").alias("lead_n")), "leaders")
    star = members.join(leaders.hint("merge"), "key").filter(F.col("id") != F.col("lead")).filter(_fits(F.col("n"), F.col("lead_n"), percent))
    swap = F.col("id") < F.col("lead")
    star = star.select(F.least("id", "lead").alias("a"), F.greatest("id", "lead").alias("b"), F.when(swap, F.col("n")).otherwise(F.col("lead_n")).alias("n"), F.when(swap, F.col("lead_n")).otherwise(F.col("n")).alias("m")).distinct()
    star = materialize(spark, star, "star-pairs")
    seen = materialize(spark, star.join(intersections(star, sets).hint("merge"), ["a", "b"]), "star-intersections")
    links = seen.filter(_similar(F.col("both"), F.col("n"), F.col("m"), percent)).select("a", "b")
    comps = components(spark, links)
    # Buckets that still hold several components: confirm what is left across them.
    labelled = members.join(comps.hint("merge"), "id", "left").select("key", "c", "id", "n", F.coalesce("comp", "id").alias("comp"))
    mixed = labelled.groupBy("key").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).filter("lo < hi").select("key").hint("merge")
    open_ = materialize(spark, labelled.join(mixed, "key", "left_semi"), "mixed-buckets")
    some = small_side(open_.select("id").distinct())
    codes = named.select(F.col("doc_id").alias("id"), "ga", "gb").join(some, "id", "left_semi").distinct().hint("merge")
    open_ = open_.join(sketches(sets.join(some, "id", "left_semi")).hint("merge"), "id").join(codes, "id")
    rest = across_components(open_, percent, bits)
    rest = materialize(spark, rest.distinct().join(star.select("a", "b").hint("merge"), ["a", "b"], "left_anti"), "rest-pairs")
    found = rest.join(intersections(rest, sets).hint("merge"), ["a", "b"]).filter(_similar(F.col("both"), F.col("n"), F.col("m"), percent))
    more = materialize(spark, found.select("a", "b"), "more-links")
    if not more.isEmpty():
        comps = components(spark, links.unionByName(more))
    rows_ = base.select("doc_id", "n", "s1", "s2").join(classes.hint("merge"), ["s1", "s2", "n"], "left")
    rows_ = rows_.join(comps.select(F.col("id").alias("rep"), "comp").hint("merge"), "rep", "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("comp", "rep", "doc_id"))
    return rows_.select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"), F.coalesce(component == F.col("doc_id"), F.lit(True)).alias("kept"))


@tidy
def drop_near_copies(spark: SparkSession, docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """docs with one document, the smallest doc_id, of each component; columns unchanged.

    Rows that share a doc_id are one document: if any of their texts links to a smaller doc_id, all of them go. Rows without doc_id stay.
    """
    lost = materialize(spark, near_components(spark, docs, k, percent).filter(~F.col("kept")).select("doc_id").distinct(), "near-copies")
    return docs.join(small_side(lost), "doc_id", "left_anti").select(*docs.columns)


def op1_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_components(spark, table(spark, sf_dir, "documents"), k=3, percent=85)
