"""Exact nearest rows and similar pairs of vectors, without a vector of the pool on the driver.

A reference (curated rows, or the picks of a selection) goes round in blocks of bounded size, one broadcast at a time.
All pairs of one set over a similarity meet in cells around pivots: a row belongs to the cell of its nearest pivot and
visits the cells that are at most twice the angle further away, so by the triangle inequality every similar pair meets in the
home cell of its smaller id. Large cells are dealt out as pairs of blocks. Where the angle is so wide that cells would copy
rows many times, which is counted first, the rows themselves go round in blocks instead and nothing is copied.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import vectors as V
from ..sources.tables import stage
from .select import DEFAULT, SelectionPlanner, top_q_per_group

REF_BLOCK = 4096  # reference rows that are broadcast and compared with at a time, about
PIVOTS, CELL_BLOCK = 64, 2048
COPIES = 8  # copies of a row, on average, that cells may exchange
BLOCK_BYTES = 64 << 20  # of a block of the set's own rows
TILE_ROWS, TILE_REFS = 1024, 2048  # rows that are multiplied at a time


def _unit(vectors: DataFrame) -> DataFrame:
    return vectors.select("sample_id", V.l2_normalize(F.col("vec")).alias("z")).filter("z IS NOT NULL")


def by_blocks(pool: DataFrame, ref: DataFrame, rows: int, compare: Callable, schema: str, merge: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """merge(union over the blocks of merge(pool rows compared with a block)); compare(ids, z, own ids, own z) gives a record batch.

    A block's broadcast is released before the next one is read; the reference itself stays in a table.
    """
    return _by_blocks(pool, stage(pool.sparkSession, _unit(ref), "reference"), rows, lambda ids, z, batches: (compare(ids, z, *own) for own in batches), schema, merge)


def _by_blocks(pool: DataFrame, unit: DataFrame, rows: int, compare: Callable, schema: str, merge: Callable[[DataFrame], DataFrame], keep: bool = False) -> DataFrame:
    """As by_blocks, with unit (sample_id, z) as a table; compare(ids, z, iterator of own ids and own z) sees a whole task and gives record batches.

    keep: a single block's result becomes a table too.
    """
    spark = pool.sparkSession
    n = -(-unit.count() // rows)

    def against(part: DataFrame):
        t = part.orderBy("sample_id").toArrow()  # a block
        if not t.num_rows:
            return spark.createDataFrame([], schema), None
        shared = spark.sparkContext.broadcast((t["sample_id"].to_numpy(), V.matrix(t["z"])[0]))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            ids, z = shared.value
            yield from compare(ids, z, (own_rows(batch, z.shape[1]) for batch in batches))

        return merge(pool.select("sample_id", "vec").mapInArrow(run, schema)), shared

    if n <= 1 and not keep:
        return against(unit)[0]
    out, n = None, max(n, 1)
    for block in range(n):
        found, shared = against(unit.filter(F.pmod(F.xxhash64("sample_id"), F.lit(n)) == block))
        found = stage(spark, found, "block")
        if shared is not None:
            shared.destroy()
        out = found if out is None else out.unionByName(found)
    return merge(out)


def own_rows(batch: pa.RecordBatch, d: int) -> tuple[np.ndarray, np.ndarray]:
    """Ids and unit vectors of a batch (sample_id, vec), without rows that have none."""
    x, valid = V.matrix(batch.column(1), d)
    u, ok = V.unit_rows(x)
    return np.asarray(batch.column(0))[valid[ok]], u[ok]


def nearest_rows(pool: DataFrame, ref: DataFrame, m: int, block: int = REF_BLOCK, planner: SelectionPlanner = DEFAULT) -> DataFrame:
    """(ref_id, sample_id, sim): the m pool rows nearest to each reference row, similarities rounded to 9 digits."""

    unit = stage(pool.sparkSession, _unit(ref), "reference")
    return _by_blocks(pool, unit, block, lambda ids, z, batches: running_top(ids, z, batches, m), FOUND, lambda df: top_q_per_group(df, "ref_id", m, "sim", "sample_id", planner))


FOUND = "ref_id long, sample_id long, sim double"


def running_top(ids: np.ndarray, z: np.ndarray, batches: Iterator[tuple[np.ndarray, np.ndarray]], m: int, best: bool = False) -> Iterator[pa.RecordBatch]:
    """(ref_id, sample_id, sim): the m rows of a task nearest to each reference row; with best also each row's largest similarity, under no ref_id.

    Similarities with references are rounded to 9 digits, smaller ids go first. Once m rows are held, only what reaches the
    least of them is sorted.
    """
    top, who = np.full((len(ids), m), -np.inf), np.full((len(ids), m), np.iinfo(np.int64).max)
    for mine, u in batches:
        most = np.full(len(mine), -np.inf)
        for i in range(0, len(mine), TILE_ROWS):
            own, x = mine[i : i + TILE_ROWS], u[i : i + TILE_ROWS]
            for j in range(0, len(ids), TILE_REFS):
                sim = x @ z[j : j + TILE_REFS].T
                if best:
                    np.maximum(most[i : i + len(x)], sim.max(axis=1), out=most[i : i + len(x)])
                floor = top[j : j + TILE_REFS, -1]
                if len(x) > m and np.isinf(floor).any():
                    floor = np.maximum(floor, np.partition(sim, len(x) - m, axis=0)[len(x) - m])
                at, ref = np.divmod(np.flatnonzero(sim >= floor - 1e-9), sim.shape[1])
                value, found, ref = np.round(sim[at, ref], 9), own[at], ref + j
                use = (value > top[ref, -1]) | ((value == top[ref, -1]) & (found < who[ref, -1]))
                if not use.any():
                    continue
                value, found, ref = value[use], found[use], ref[use]
                some = np.unique(ref)
                value, found, ref = np.concatenate([value, top[some].ravel()]), np.concatenate([found, who[some].ravel()]), np.concatenate([ref, np.repeat(some, m)])
                order = np.lexsort((found, -value, ref))
                begin = np.searchsorted(ref[order], some)
                order = order[begin[:, None] + np.arange(m)]
                top[some], who[some] = value[order], found[order]
        if best:
            yield pa.RecordBatch.from_arrays([pa.nulls(len(mine), pa.int64()), pa.array(mine), pa.array(most)], ["ref_id", "sample_id", "sim"])
    for j in range(0, len(ids), TILE_REFS):
        row, at = np.nonzero(np.isfinite(top[j : j + TILE_REFS]))
        yield pa.RecordBatch.from_arrays([pa.array(ids[row + j]), pa.array(who[row + j, at]), pa.array(top[row + j, at])], ["ref_id", "sample_id", "sim"])


def retrieved(pool: DataFrame, ref: DataFrame, m: int, block: int | None = None, planner: SelectionPlanner = DEFAULT) -> DataFrame:
    """(sample_id, best, hit): largest cosine with any reference row, and whether some reference row has the row among its m nearest.

    Both come from one multiplication of all rows with all references.
    """
    spark = pool.sparkSession
    unit = stage(spark, _unit(ref), "reference")
    first = unit.limit(1).toArrow()
    rows = block or (max(TILE_REFS, BLOCK_BYTES // (8 * len(first["z"][0]))) if first.num_rows else 1)
    found = _by_blocks(pool, unit, rows, lambda ids, z, batches: running_top(ids, z, batches, m, True), FOUND, lambda df: df, keep=True)
    hits = top_q_per_group(found.filter("ref_id IS NOT NULL"), "ref_id", m, "sim", "sample_id", planner).select("sample_id").distinct()
    best = found.filter("ref_id IS NULL").groupBy("sample_id").agg(F.max("sim").alias("best"))
    return best.join(hits.withColumn("hit", F.lit(True)), "sample_id", "left").withColumn("hit", F.coalesce("hit", F.lit(False)))


def best_similarity(pool: DataFrame, ref: DataFrame, block: int = REF_BLOCK) -> DataFrame:
    """(sample_id, best): largest cosine with any reference row."""

    def compare(ids, z, mine, u):
        return pa.RecordBatch.from_arrays([pa.array(mine), pa.array((u @ z.T).max(axis=1) if len(u) else np.zeros(0))], ["sample_id", "best"])

    return by_blocks(pool, ref, block, compare, "sample_id long, best double", lambda df: df.groupBy("sample_id").agg(F.max("best").alias("best")))


def similar_pairs(vectors: DataFrame, least: float, pivots: int = PIVOTS, block: int = CELL_BLOCK) -> DataFrame:
    """(a, b, sim) with a < b and cosine, rounded to 9 digits, of at least least. Rows without a unit vector have no pairs.

    Exact. The cost grows with the rows that cells share: little for near-copies, all pairs where least is low.
    """
    unit = stage(vectors.sparkSession, _unit(vectors), "unit")
    pairs = _in_cells(unit, least, pivots, block)
    return _in_blocks(unit, least) if pairs is None else pairs


def similar_rows(vectors: DataFrame, least: float, later: bool = False, pivots: int = PIVOTS, block: int = CELL_BLOCK) -> DataFrame:
    """(sample_id): rows that some other row, with later one of smaller id, resembles to least or more. Exact, as similar_pairs is.

    In blocks a row is not compared any further once another one is found, and no pair leaves its task.
    """
    unit = stage(vectors.sparkSession, _unit(vectors), "unit")
    pairs = _in_cells(unit, least, pivots, block)
    if pairs is None:
        return _in_blocks(unit, least, "later" if later else "any")
    return pairs.select(F.col("b").alias("sample_id") if later else F.explode(F.array("a", "b")).alias("sample_id")).distinct()


def _in_blocks(unit: DataFrame, least: float, kind: str = "pairs") -> DataFrame:
    """All rows against blocks of the rows: pairs (a, b, sim), or (sample_id) of the rows that have any, or an earlier, similar row."""
    first = unit.limit(1).toArrow()
    if not first.num_rows:
        return unit.sparkSession.createDataFrame([], "a long, b long, sim double" if kind == "pairs" else "sample_id long")
    rows = max(TILE_REFS, BLOCK_BYTES // (8 * len(first["z"][0])))
    tasks = max(2 * unit.sparkSession.sparkContext.defaultParallelism, -(-unit.count() // (2 * TILE_ROWS)))
    pool = unit.withColumnRenamed("z", "vec").repartition(tasks, "sample_id")
    compare = lambda ids, z, batches: (found for own in batches for found in tiles(ids, z, *own, least, kind))
    if kind == "pairs":
        return _by_blocks(pool, unit, rows, compare, "a long, b long, sim double", lambda df: df)
    return _by_blocks(pool, unit, rows, compare, "sample_id long", lambda df: df.distinct())


def tiles(ids: np.ndarray, z: np.ndarray, mine: np.ndarray, u: np.ndarray, least: float, kind: str) -> Iterator[pa.RecordBatch]:
    """What _in_blocks finds of the rows mine with unit vectors u in a block of ids, ascending, with unit vectors z; tile by tile."""
    order = np.argsort(mine, kind="stable")
    mine, u = mine[order], u[order]
    for i in range(0, len(mine), TILE_ROWS):
        own, x = mine[i : i + TILE_ROWS], u[i : i + TILE_ROWS]
        end = len(ids) if kind == "any" else int(np.searchsorted(ids, own[-1]))
        for j in range(0, end, TILE_REFS):
            ref = ids[j : min(end, j + TILE_REFS)]
            sim = x @ z[j : j + len(ref)].T
            at, to = np.divmod(np.flatnonzero(sim >= least - 1e-8), len(ref))
            sim = sim[at, to]
            hit = (np.round(sim, 9) >= least) & (ref[to] != own[at] if kind == "any" else ref[to] < own[at])
            at, to = at[hit], to[hit]
            if kind == "pairs":
                if len(at):
                    yield pa.RecordBatch.from_arrays([pa.array(ref[to]), pa.array(own[at]), pa.array(sim[hit])], ["a", "b", "sim"])
                continue
            found = np.zeros(len(own), bool)
            found[at] = True
            yield pa.RecordBatch.from_arrays([pa.array(own[found])], ["sample_id"])
            own, x = own[~found], x[~found]
            if not len(own):
                break


def _in_cells(unit: DataFrame, least: float, pivots: int, block: int) -> DataFrame | None:
    """The pairs (a, b, sim) by cells; None where those would exchange more than COPIES copies of a row."""
    spark = unit.sparkSession
    first = unit.orderBy(F.xxhash64("sample_id"), "sample_id").limit(pivots).toArrow()
    if not first.num_rows:
        return spark.createDataFrame([], "a long, b long, sim double")
    centres = spark.sparkContext.broadcast(V.matrix(first["z"])[0])
    reach = 2 * math.acos(min(1.0, max(-1.0, least - 1e-9))) + 1e-6

    def near(z: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        angle = np.arccos(np.clip(z @ centres.value.T, -1, 1))
        return angle.argmin(axis=1), angle <= angle.min(axis=1)[:, None] + reach

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = np.zeros(len(centres.value), np.int64)
        for batch in batches:
            n += near(V.matrix(batch.column(0), centres.value.shape[1])[0])[1].sum(axis=0)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(n))), pa.array(n)], ["cell", "n"])

    counts = [r["n"] for r in unit.select("z").mapInArrow(count, "cell long, n long").groupBy("cell").agg(F.sum("n").alias("n")).collect()]  # a row for each pivot
    if sum(n * -(-n // block) for n in counts) > COPIES * unit.count():
        centres.destroy()
        return None

    def to_cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            home, reached = near(V.matrix(batch.column(1), centres.value.shape[1])[0])
            row, cell = np.nonzero(reached)
            yield pa.RecordBatch.from_arrays([pa.array(cell), pa.array(home[row] == cell), batch.column(0).take(pa.array(row)), batch.column(1).take(pa.array(row))], ["cell", "home", "id", "z"])

    cells = stage(spark, unit.mapInArrow(to_cells, "cell long, home boolean, id long, z array<double>"), "cells")
    sizes = cells.groupBy("cell").agg(F.ceil(F.count(F.lit(1)) / block).cast("int").alias("blocks"))  # a row for each pivot
    dealt = cells.join(F.broadcast(sizes), "cell").withColumn("u", F.pmod(F.xxhash64("id"), "blocks").cast("int"))
    dealt = dealt.withColumn("v", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.select("cell", F.least("u", "v").alias("p"), F.greatest("u", "v").alias("q"), "u", "home", "id", "z")

    def pairs(held: list[pa.RecordBatch]) -> pa.RecordBatch:
        t = pa.Table.from_batches(held).sort_by("id")
        z, ids, home, u = V.matrix(t["z"])[0], t["id"].to_numpy(), t["home"].to_numpy(zero_copy_only=False), t["u"].to_numpy()
        sim = z[home] @ z.T
        hit = (np.round(sim, 9) >= least) & (ids[home][:, None] < ids)
        if held[0].column(1)[0] != held[0].column(2)[0]:
            hit &= u[home][:, None] != u
        i, j = np.nonzero(hit)
        return pa.RecordBatch.from_arrays([pa.array(ids[home][i]), pa.array(ids[j]), pa.array(sim[i, j])], ["a", "b", "sim"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, last = [], None  # the cell at the end of a batch may go on in the next
        for batch in batches:
            if not batch.num_rows:
                continue
            key = np.column_stack([batch.column(c).to_numpy() for c in range(3)])
            edges = [0, *(np.flatnonzero((key[1:] != key[:-1]).any(axis=1)) + 1).tolist(), len(key)]
            for i, j in zip(edges[:-1], edges[1:], strict=True):
                if held and tuple(key[i]) != last:
                    yield pairs(held)
                    held = []
                held.append(batch.slice(i, j - i))
                last = tuple(key[i])
        if held:
            yield pairs(held)

    return dealt.repartition("cell", "p", "q").sortWithinPartitions("cell", "p", "q").mapInArrow(run, "a long, b long, sim double")


def drop_near_copies(vectors: DataFrame, least: float) -> DataFrame:
    """vectors without the rows that a row of smaller id resembles to least or more: the copy removal before retrieval."""
    copies = stage(vectors.sparkSession, similar_rows(vectors, least, later=True), "copies")
    return vectors.join(copies, "sample_id", "left_anti")
