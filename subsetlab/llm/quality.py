"""Document quality by a linear-chain conditional random field over lines.

Every line is good or bad; its features are shares of character kinds and word shapes of the line itself, of the line
before and of the line after. Training takes each line's label from its document and maximises the penalised
conditional likelihood. A document's score is the mean of its lines' forward-backward marginals of good, weighted by
line length.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import released, table, text_buffer
from .kernels import LOWER, SPACE, span_hashes, word_spans
from .line_dedup import line_spans

TRAIN_ROWS = 1500  # labelled documents of each label that training takes at most
TRAIN_LINES = 512  # labelled documents of more lines take no part in training, so 2 * TRAIN_ROWS * TRAIN_LINES lines of 212 bytes bound what it gathers
THRESHOLD = 0.3
FOLDS = 5

_KINDS = np.zeros((8, 256), bool)
_KINDS[0, 65:91] = True  # capitals
_KINDS[1, 97:123] = True
_KINDS[1, 128:] = True  # bytes of other letters count as small ones
_KINDS[2, 48:58] = True
_KINDS[3, [ord("|")]] = True
_KINDS[4, [ord("!")]] = True
_KINDS[5, [ord(c) for c in "#$%&*@^~<>{}[]\\_=+"]] = True
_KINDS[6, [ord(c) for c in ".,;:?"]] = True
_KINDS[7] = SPACE
N_OWN = 17
N_FEATURES = 3 * N_OWN + 2


def line_features(data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(lines, N_FEATURES) float32 features, line weights (bytes, 1 at least) and each row's first line."""
    starts, ends, first = line_spans(data, offs)
    size = (ends - starts).astype(np.float32)

    def per_line(flags: np.ndarray) -> np.ndarray:
        sums = np.concatenate(([0], np.cumsum(flags, dtype=np.int32)))
        return (sums[ends] - sums[starts]).astype(np.float32)

    n = [per_line(k[data]) for k in _KINDS]
    low = LOWER[data]
    begin, stop, at = word_spans(low, np.append(starts, len(data)))  # a line's words: at[i] up to at[i + 1]
    words = np.maximum(np.diff(at), 1).astype(np.float32)
    h = span_hashes(low, begin, stop) if len(begin) else np.zeros(0, np.uint64)
    again = np.zeros((2, len(h) + 1), np.int32)
    line = np.repeat(np.arange(len(starts)), np.diff(at))
    for lag in (1, 2):  # words that repeat the one before, or the one before that
        again[lag - 1, lag + 1 :] = (h[lag:] == h[:-lag]) & (line[lag:] == line[:-lag])
    again = again.cumsum(axis=1)
    repeats = (again[:, at[1:]] - again[:, at[:-1]]) / words
    letters = np.maximum(n[0] + n[1], 1)
    full = np.maximum(size, 1)
    own = np.column_stack([
        np.ones(len(size), np.float32), np.minimum(np.log1p(size) / 8, 1), size == 0, n[0] / letters, (n[0] > 0.6 * letters).astype(np.float32), n[2] / full,
        np.minimum(n[3] / words, 1), np.minimum(n[4] / words, 1), np.minimum(n[5] / words / 3, 1), np.minimum(n[6] / words, 1), np.minimum(n[7] / full, 1),
        np.minimum(full / words / 16, 1), np.minimum(words / 8, 1), n[3] > 0, n[4] + n[5] > 0, repeats[0], repeats[1],
    ]).astype(np.float32)
    before, after = np.roll(own, 1, axis=0), np.roll(own, -1, axis=0)
    at_start, at_end = np.zeros(len(size), bool), np.zeros(len(size), bool)
    at_start[first[:-1]] = at_end[first[1:] - 1] = True
    before[at_start] = after[at_end] = 0
    return np.column_stack([own, before, after, at_start, at_end]).astype(np.float32), full, first


class LineField:
    """Two labels (0 bad, 1 good): weights w give a line's score for good against bad, moves[a, b] that of a step from a to b."""

    def __init__(self, weights: np.ndarray | None = None, moves: np.ndarray | None = None):
        self.w = np.zeros(N_FEATURES) if weights is None else weights
        self.moves = np.zeros((2, 2)) if moves is None else moves

    def _sweep(self, lines: np.ndarray, first: np.ndarray):
        """Log forward and backward scores (lines, 2), all rows side by side; rows have one line at least."""
        size = np.diff(first)
        order = np.argsort(-size, kind="stable")
        begin, stop, ascending = first[:-1][order], first[1:][order] - 1, size[order][::-1]
        local = np.column_stack([np.zeros(len(lines)), lines])
        ahead, back = local.copy(), np.zeros_like(local)
        m = self.moves
        for t in range(1, int(size.max()) if len(size) else 0):
            k = len(size) - int(np.searchsorted(ascending, t, "right"))
            at = begin[:k] + t
            prev = ahead[at - 1]
            ahead[at, 0] += np.logaddexp(prev[:, 0] + m[0, 0], prev[:, 1] + m[1, 0])
            ahead[at, 1] += np.logaddexp(prev[:, 0] + m[0, 1], prev[:, 1] + m[1, 1])
            at = stop[:k] - t
            nxt = back[at + 1] + local[at + 1]
            back[at, 0] = np.logaddexp(nxt[:, 0] + m[0, 0], nxt[:, 1] + m[0, 1])
            back[at, 1] = np.logaddexp(nxt[:, 0] + m[1, 0], nxt[:, 1] + m[1, 1])
        return local, ahead, back

    def marginals(self, x: np.ndarray, first: np.ndarray) -> np.ndarray:
        """Probability of good for every line."""
        _, ahead, back = self._sweep(x @ self.w, first)
        s = ahead + back
        return 1 / (1 + np.exp(np.clip(s[:, 0] - s[:, 1], -60, 60)))

    def objective(self, theta: np.ndarray, x: np.ndarray, first: np.ndarray, y: np.ndarray, v: np.ndarray, penalty: float) -> tuple[float, np.ndarray]:
        """Penalised mean log-likelihood of the lines' labels y under line weights v (equal within a row), and its gradient; sets the weights to theta."""
        self.w, self.moves = theta[:N_FEATURES], theta[N_FEATURES:].reshape(2, 2)
        inner = np.ones(len(y), bool)
        inner[first[:-1]] = False
        second = np.flatnonzero(inner)
        seen = np.zeros((2, 2))
        np.add.at(seen, (y[second - 1], y[second]), v[second])
        local, ahead, back = self._sweep(x @ self.w, first)
        s = ahead + back
        total = np.logaddexp(s[:, 0], s[:, 1])  # a row's log-partition, at each of its lines
        good = np.exp(s[:, 1] - total)
        grad = np.empty_like(theta)
        grad[:N_FEATURES] = x.T @ (v * (y - good))
        pair = ahead[second - 1][:, :, None] + self.moves + (local[second] + back[second])[:, None, :] - total[second][:, None, None]
        grad[N_FEATURES:] = (seen - (np.exp(pair) * v[second][:, None, None]).sum(axis=0)).ravel()
        value = v @ local[np.arange(len(y)), y] + (seen * self.moves).sum() - v[first[:-1]] @ total[first[:-1]]
        scale = v.sum()
        return value / scale - penalty * theta @ theta / 2, grad / scale - penalty * theta

    def fit(self, x: np.ndarray, first: np.ndarray, label: np.ndarray, weight: np.ndarray, steps: int = 100, rate: float = 0.2, penalty: float = 1e-3) -> LineField:
        """label and weight are a row's; gradient ascent with adaptive moments."""
        rows = np.repeat(np.arange(len(label)), np.diff(first))
        y, v, x = label[rows], weight[rows], x.astype(np.float64)
        theta, m1, m2 = np.zeros(N_FEATURES + 4), 0.0, 0.0
        for step in range(1, steps + 1):
            _, grad = self.objective(theta, x, first, y, v, penalty)
            m1, m2 = 0.9 * m1 + 0.1 * grad, 0.99 * m2 + 0.01 * grad**2
            theta = theta + rate * (m1 / (1 - 0.9**step)) / (np.sqrt(m2 / (1 - 0.99**step)) + 1e-8)
        self.w, self.moves = theta[:N_FEATURES], theta[N_FEATURES:].reshape(2, 2)
        return self

    def scores(self, data: np.ndarray, offs: np.ndarray) -> np.ndarray:
        """Length-weighted mean marginal of every row."""
        if len(offs) < 2:
            return np.zeros(0)
        out = []
        i, n = 0, len(offs) - 1
        while i < n:
            j = max(i + 1, int(np.searchsorted(offs, offs[i] + (1 << 20), "right")) - 1)
            x, size, first = line_features(data[offs[i] : offs[j]], offs[i : j + 1] - offs[i])
            p = self.marginals(x, first) * size
            out.append(np.add.reduceat(p, first[:-1]) / np.add.reduceat(size, first[:-1]))
            i = j
        return np.clip(np.concatenate(out), 0, 1)


def held_out(doc_id) -> F.Column:
    return F.crc32(doc_id.cast("string").cast("binary")) % FOLDS == 0


def train(docs: DataFrame, labels: DataFrame, rows: int = TRAIN_ROWS, lines: int = TRAIN_LINES) -> LineField:
    """Fit on at most rows labelled documents of each label, chosen by hash, none of the held-out fold, none of over lines lines.

    Rows without label or id are left out. Without both labels the field stays flat and scores every line 0.5.
    """
    usable = labels.select("doc_id", "quality").filter(F.col("quality").isin(0, 1) & ~held_out(F.col("doc_id")))
    chosen = None
    for q in (0, 1):
        part = usable.filter(F.col("quality") == q).orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
        chosen = part if chosen is None else chosen.unionByName(part)
    sample = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id")  # at most 2 * rows ids

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in released(batches):
            x, _, first = line_features(*text_buffer(batch.column(1)))
            lists = [x[a:b].tobytes() for a, b in zip(first[:-1], first[1:], strict=True)]
            all_ = pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(lists, pa.binary())], ["doc_id", "quality", "x"])
            yield all_.filter(pa.array(np.diff(first) <= lines))

    got = sample.mapInArrow(run, "doc_id long, quality int, x binary").toArrow().sort_by([("doc_id", "ascending"), ("x", "ascending")])
    label = got.column("quality").to_numpy().astype(np.int64)
    if len(np.unique(label)) < 2:
        return LineField()
    parts = [np.frombuffer(b, np.float32).reshape(-1, N_FEATURES) for b in got.column("x").to_pylist()]
    first = np.concatenate(([0], np.cumsum([len(p) for p in parts])))
    per_line = np.sqrt(1 / np.diff(first))  # long documents count more than short ones, but not by the line
    share = np.bincount(label, weights=per_line * np.diff(first), minlength=2)
    return LineField().fit(np.concatenate(parts), first, label, per_line * share.sum() / (2 * share[label]))


def quality_scores(spark: SparkSession, docs: DataFrame, labels: DataFrame, rows: int = TRAIN_ROWS, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, held_out, score, predicted: one row per input row.

    Null text counts as empty: one empty line. A null doc_id has held_out null. Only the text enters a score; extra columns are ignored.
    """
    field = spark.sparkContext.broadcast(train(docs, labels, rows))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in released(batches):
            s = field.value.scores(*text_buffer(batch.column(1)))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(s), pa.array((s >= threshold).astype(np.int32))], ["doc_id", "score", "predicted"])

    out = docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, score double, predicted int")
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")


def keep_good(spark: SparkSession, docs: DataFrame, labels: DataFrame, rows: int = TRAIN_ROWS, threshold: float = THRESHOLD) -> DataFrame:
    """docs whose score reaches the threshold; columns and rows unchanged otherwise."""
    field = spark.sparkContext.broadcast(train(docs, labels, rows))
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in released(batches):
            yield batch.filter(pa.array(field.value.scores(*text_buffer(batch.column(at))) >= threshold))

    return docs.mapInArrow(run, docs.schema)


def op6_line_field_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_scores(spark, table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
