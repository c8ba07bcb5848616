"""Best-fit packing of token pieces into sequences by hierarchical residual packing.

Leaves pack their own pieces, longest first, each into the open bin with the least room that still fits. Bins without
useful room are final. The others go up a tree of merge nodes, where they are items themselves and are packed best-fit
again. Two bins can share a sequence only if one of them is at most half full, and best-fit leaves at most one such bin
in a node. So a merge node sees at most FAN_IN half-empty bins and needs no more than FAN_IN hosts for them. A node
passes up its half-empty bin and, of the rest, the FAN_IN roomiest for each level above it, which is all that could
ever be used there: a merge node holds some FAN_IN * FAN_IN * levels bins at most, whatever the number of pieces.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from .common import materialize, released, small_side, table, tidy
from .word_bpe import word_bpe

CAPACITY = 2048
LEAF_PIECES = 50_000
FAN_IN = 16


def best_fit(sizes: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bin and offset of every item, and the bins' fill. Longest first; ties by position; sizes of 1 to capacity."""
    order = np.argsort(-sizes, kind="stable")
    bins, offset = np.empty(len(sizes), np.int64), np.empty(len(sizes), np.int64)
    fill: list[int] = []
    open_: list[list[int]] = [[] for _ in range(capacity + 1)]  # by room
    rooms = 0  # bit r: some bin has room r
    for i, size in zip(order.tolist(), sizes[order].tolist(), strict=True):
        fits = rooms >> size
        if fits:
            room = size + (fits & -fits).bit_length() - 1
            stack = open_[room]
            b = stack.pop()
            if not stack:
                rooms ^= 1 << room
        else:
            room, b = capacity, len(fill)
            fill.append(0)
        bins[i], offset[i] = b, fill[b]
        fill[b] += size
        room -= size
        if room:
            open_[room].append(b)
            rooms |= 1 << room
    return bins, offset, np.array(fill, np.int64)


def _levels(nodes: int) -> int:
    """Merge levels above so many nodes."""
    return 0 if nodes <= 1 else 1 + _levels(-(-nodes // FAN_IN))


def _passed_up(fill: np.ndarray, capacity: int, levels: int, slack: int) -> np.ndarray:
    """Which bins go to the next node, with so many merge levels above."""
    rest = np.flatnonzero((fill > capacity // 2) & (fill < capacity - slack))
    rest = rest[np.argsort(fill[rest], kind="stable")[: FAN_IN * levels]]
    up = fill <= capacity // 2
    up[rest] = True
    return up


def pack(spark: SparkSession, pieces: DataFrame, capacity: int = CAPACITY, size: str = "length", leaf_pieces: int = LEAF_PIECES, slack: int = 0) -> DataFrame:
    """pieces plus sequence_id and offset; no sequence is over capacity, offsets are gapless from 0.

    pieces must be re-readable at the same rows (a table). Sizes are 1 to capacity, else it raises; null sizes raise too.
    Repeated rows are packed as items of their own. An empty table gives no rows.
    """
    if {"sequence_id", "offset"} & set(pieces.columns):
        raise ValueError("pieces already has sequence_id or offset")
    low, high, n, missing = pieces.agg(F.min(size), F.max(size), F.count(F.lit(1)), F.count(F.when(F.col(size).isNull(), 1))).first()
    if n and (missing or low < 1 or high > capacity):
        raise ValueError(f"sizes must be 1 to {capacity}")
    leaves = max(1, -(-n // leaf_pieces))
    out_type = StructType(list(pieces.schema.fields)).add("_node", "long").add("_bin", "long").add("offset", "long").add("_fill", "long").add("_up", "boolean")

    def leaf(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values([c for c in rows.columns if c != "_node"], kind="stable", ignore_index=True)
        bins, offset, fill = best_fit(rows[size].to_numpy(np.int64), capacity)
        up = _passed_up(fill, capacity, _levels(leaves), slack) if leaves > 1 else np.zeros(len(fill), bool)
        return rows.assign(_bin=(key[0] << 32) + bins, offset=offset, _fill=fill[bins], _up=up[bins])

    node = F.pmod(F.xxhash64(*pieces.columns), F.lit(leaves)).alias("_node")
    packed = pieces.select("*", node).groupBy("_node").applyInPandas(leaf, out_type)
    if leaves == 1:
        return packed.withColumnRenamed("_bin", "sequence_id").drop("_node", "_fill", "_up")
    packed = materialize(spark, packed, "packed")
    # each bin passed up once: (bin, node, fill); moved: where a first-level bin now lies (root bin, shift)
    bins = packed.filter("_up AND offset = 0").select(F.col("_bin").alias("bin"), F.col("_node").alias("node"), F.col("_fill").alias("fill"))
    moved, nodes = None, leaves

    def merger(levels: int):
        def merge(rows: pd.DataFrame) -> pd.DataFrame:
            rows = rows.sort_values(["fill", "bin"], ascending=[False, True], ignore_index=True)
            at, shift, fill = best_fit(rows["fill"].to_numpy(np.int64), capacity)
            host = rows["bin"].to_numpy()[np.unique(at, return_index=True)[1]]
            up = _passed_up(fill, capacity, levels, slack)
            return pd.DataFrame({"bin": rows["bin"], "root": host[at], "shift": shift, "node": rows["node"] // FAN_IN, "fill": fill[at], "up": up[at]})

        return merge

    while nodes > 1:
        nodes = -(-nodes // FAN_IN)
        step = bins.groupBy((F.col("node") / FAN_IN).cast("long").alias("parent")).applyInPandas(merger(_levels(nodes)), "bin long, root long, shift long, node long, fill long, up boolean")
        step = materialize(spark, step, "merged")
        here = step.select("bin", "root", "shift")
        if moved is None:
            moved = here
        else:
            later = here.select(F.col("bin").alias("root"), F.col("root").alias("next"), F.col("shift").alias("more"))
            moved = moved.join(later, "root", "left").select("bin", F.coalesce("next", "root").alias("root"), (F.col("shift") + F.coalesce("more", F.lit(0))).alias("shift"))
        bins = step.filter("up AND shift = 0 AND bin = root").select("bin", "node", "fill")
    moved = materialize(spark, moved, "moved").select(F.col("bin").alias("_bin"), "root", "shift")
    out = packed.join(small_side(moved), "_bin", "left")
    return out.select(*pieces.columns, F.coalesce("root", "_bin").alias("sequence_id"), (F.col("offset") + F.coalesce("shift", F.lit(0))).alias("offset"))


def tokenized_pieces(docs: DataFrame, capacity: int = CAPACITY, tokenizer: str | None = None, with_ids: bool = False) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 (and ids): a document's ids and a closing 0, cut into capacity-token pieces.

    Null text counts as empty (one piece with the closing 0). Rows are taken one by one, repeated ids included.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import public_tokenizers

        bpe = word_bpe(tokenizer or public_tokenizers.path("word_bpe_49k.json"))
        close = np.zeros(1, np.int32)
        for batch in released(batches):
            ids, texts = batch.column(0).to_pylist(), ["" if t is None else t for t in batch.column(1).to_pylist()]
            i = 0
            while i < len(texts):
                j, total = i, 0
                while j < len(texts) and (j == i or total + len(texts[j]) <= 800_000):
                    total += len(texts[j])
                    j += 1
                rows: list[tuple] = []
                for doc, own in zip(ids[i:j], bpe.encode(texts[i:j]), strict=True):
                    own = np.concatenate((own, close)).astype("<u4")
                    for k, a in enumerate(range(0, len(own), capacity)):
                        part = own[a : a + capacity]
                        rows.append((doc, k, a, len(part), zlib.crc32(part.tobytes()), *([part] if with_ids else [])))
                cols = list(zip(*rows, strict=True))
                arrays = [pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int32()), *(pa.array(c, pa.int64()) for c in cols[2:5])]
                if with_ids:
                    arrays.append(pa.array([p.astype(np.int32) for p in cols[5]], pa.list_(pa.int32())))
                yield pa.RecordBatch.from_arrays(arrays, ["doc_id", "piece", "start", "length", "ids_crc32", "ids"][: len(arrays)])
                i = j

    out = "doc_id long, piece int, start long, length long, ids_crc32 long" + ", ids array<int>" * with_ids
    return docs.select("doc_id", "text").mapInArrow(run, out)


@tidy
def pack_documents(spark: SparkSession, docs: DataFrame, capacity: int = CAPACITY, tokenizer: str | None = None) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    return pack(spark, materialize(spark, tokenized_pieces(docs, capacity, tokenizer), "pieces"), capacity)


def op9_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(spark, table(spark, sf_dir, "documents"))
