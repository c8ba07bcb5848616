"""Token counts by prefix dynamic programming.

A pair-merge tokenizer encodes a prefix as the encoding of a shorter prefix and one last piece. Piece t may end a prefix
exactly when the piece before it and t stay apart if encoded together. So one pass from left to right finds, for every
prefix, its last piece and its count, and truncation or budget questions are look-ups. An automaton of all pieces names
those that end at a position, longest first; whether two stay apart is read off the merges along their touching edges,
in the order in which the tokenizer makes them. Pieces never cross the stretches
``blanks + ink`` or a line feed, so the table of a stretch is built once and reused (bounded memory), and a text's
prefix counts are the running sums over its stretches.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import cache
from math import inf

import numpy as np
import pyarrow as pa
from ahocorasick import Automaton
from pyspark.sql import DataFrame, SparkSession

from .common import released, table

BLANK = "▁"
_STRETCH = re.compile(rf"{BLANK}*[^{BLANK}\n]+|{BLANK}+|\n")
CACHE_ENTRIES = 500_000  # stretches, and as many piece pairs, per worker
CACHE_CHARS = 64  # longer stretches are counted anew each time, so the entries' bytes are bounded too


class PrefixCounter:
    """Exact counts for a sentencepiece BPE model with identity normalisation, escaped blanks, a dummy prefix and byte fallback."""

    def __init__(self, model_file: str, cache_entries: int = CACHE_ENTRIES):
        from sentencepiece import sentencepiece_model_pb2 as pb

        model = pb.ModelProto()
        with open(model_file, "rb") as f:
            model.ParseFromString(f.read())
        norm, train = model.normalizer_spec, model.trainer_spec
        if norm.precompiled_charsmap or norm.remove_extra_whitespaces or not norm.escape_whitespaces or not train.byte_fallback or train.model_type != 2:
            raise ValueError("this model normalises or splits in a way that the prefix tables do not cover")
        self.dummy = BLANK if norm.add_dummy_prefix else ""
        self.score = {p.piece: p.score for p in model.pieces if p.type == 1}
        if any((BLANK in p.strip(BLANK)) or p.endswith(BLANK) and p.strip(BLANK) or "\n" in p for p in self.score):
            raise ValueError("pieces cross blanks or line feeds")
        self.edges: dict[str, tuple[list, list]] = {}
        self.pieces = Automaton()
        for piece in self.score:
            self.pieces.add_word(piece, piece)
        self.pieces.make_automaton()
        self.apart: dict[tuple[str, str], bool] = {}
        self.totals: dict[str, int] = {}
        self.limit = cache_entries

    def merged(self, text: str) -> list[str]:
        """Plain merging of a short text: the adjacent pair of highest score, the leftmost on ties."""
        parts, score = list(text), self.score
        while True:
            best, at = None, -1
            for i in range(len(parts) - 1):
                s = score.get(parts[i] + parts[i + 1])
                if s is not None and (best is None or s > best):
                    best, at = s, i
            if at < 0:
                return parts
            parts[at : at + 2] = [parts[at] + parts[at + 1]]

    def _edges(self, piece: str) -> tuple[list, list]:
        """(part, score) of the parts that grow along a piece's left and right edge until it is whole, in the order of merging."""
        known = self.edges.get(piece)
        if known is None:
            parts, score, left, right = list(piece), self.score, [(piece[0], 0.0)], [(piece[-1], 0.0)]
            while len(parts) > 1:
                ranked = [(score.get(a + b, -inf), -i) for i, (a, b) in enumerate(zip(parts, parts[1:], strict=False))]
                best, at = max(ranked)
                if best == -inf:
                    raise ValueError(f"no merges lead to the piece {piece!r}")
                at = -at
                parts[at : at + 2] = [parts[at] + parts[at + 1]]
                if at == 0:
                    left.append((parts[0], best))
                if at == len(parts) - 1:
                    right.append((parts[-1], best))
            if any(x[1] < y[1] for edge in (left, right) for x, y in zip(edge[1:], edge[2:], strict=False)):
                raise ValueError(f"the merges of {piece!r} are out of order")
            known = self.edges[piece] = (left, right)
        return known

    def _stay_apart(self, left: str, right: str) -> bool:
        """Whether left and right, written together, are encoded as these two pieces: no merge across their border comes first."""
        key = (left, right)
        known = self.apart.get(key)
        if known is None:
            if len(self.apart) >= self.limit:
                self.apart.clear()
            known = self.apart[key] = self._no_merge_across(left, right)
        return known

    def _no_merge_across(self, left: str, right: str) -> bool:
        if len(left) > 1 and left not in self.score or len(right) > 1 and right not in self.score:
            return self.merged(left + right) == [left, right]
        ends, begins, score = self._edges(left)[1], self._edges(right)[0], self.score
        i = j = 0
        while True:
            across = score.get(ends[i][0] + begins[j][0], -inf)
            before = ends[i + 1][1] if i + 1 < len(ends) else -inf
            after = begins[j + 1][1] if j + 1 < len(begins) else -inf
            if across > before and across >= after:  # of equal scores the leftmost is merged
                return False
            if before == after == -inf:
                return True
            if before >= after:
                i += 1
            else:
                j += 1

    def prefixes(self, stretch: str) -> list[int]:
        """Token count of every prefix of a stretch, from the empty one on."""
        apart, known, score = self._stay_apart, self.apart, self.score
        counts, last = [0], [""]

        def unknown_up_to(end: int) -> None:
            for c in stretch[len(counts) - 1 : end]:  # characters outside the pieces, written as their bytes
                if c in score:
                    raise AssertionError(f"no last piece for {stretch[: len(counts)]!r}")
                counts.append(counts[-1] + len(c.encode()))
                last.append(c)

        for at, piece in self.pieces.iter(stretch):
            if at + 1 < len(counts):
                continue  # a longer piece ends here
            if at >= len(counts):
                unknown_up_to(at)
            begin = at + 1 - len(piece)
            if begin:
                fits = known.get((last[begin], piece))
                if not (apart(last[begin], piece) if fits is None else fits):
                    continue
            counts.append(counts[begin] + 1)
            last.append(piece)
        unknown_up_to(len(stretch))
        return counts

    def total(self, stretch: str) -> int:
        known = self.totals.get(stretch)
        if known is None:
            known = self.prefixes(stretch)[-1]
            if len(stretch) <= CACHE_CHARS:
                if len(self.totals) >= self.limit:
                    self.totals.clear()
                self.totals[stretch] = known
        return known

    def stretches(self, text: str) -> list[str]:
        return _STRETCH.findall(self.dummy + text.replace(" ", BLANK)) if text else []

    def count(self, text: str) -> int:
        parts, known = self.stretches(text), self.totals
        try:
            return sum(map(known.__getitem__, parts))
        except KeyError:
            return sum(map(self.total, parts))

    def prefix_counts(self, text: str) -> np.ndarray:
        """counts[i]: tokens of the first i code points of text (the dummy prefix belongs to the first of them)."""
        out, base = [0], 0
        for k, part in enumerate(self.stretches(text)):
            own = self.prefixes(part)
            skip = 1 + (k == 0 and bool(self.dummy))
            out.extend(base + c for c in own[skip:])
            base += own[-1]
        return np.array(out, np.int64)

    def fitting(self, text: str, budget: int) -> int:
        """Most leading code points whose encoding has at most budget tokens, without re-encoding."""
        within = np.flatnonzero(self.prefix_counts(text) <= budget)
        return int(within[-1])


@cache
def counter(model_file: str) -> PrefixCounter:
    return PrefixCounter(model_file)


def token_counts(docs: DataFrame, model_file: str | None = None, limit: int = 4096, prefixes: bool = False) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit (and prefix_counts array<long>, one entry for each code point and the empty prefix).

    model_file None takes the public model at its place on every worker. Null text counts as empty: 0 bytes, 0 tokens.
    One row per input row; other columns are ignored.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import public_tokenizers

        own = counter(model_file or public_tokenizers.path("piece_bpe_32k.model"))
        for batch in released(batches):
            texts = ["" if t is None else t for t in batch.column(1).to_pylist()]
            n_bytes = [len(t) if t.isascii() else len(t.encode()) for t in texts]
            if prefixes:
                tables = [own.prefix_counts(t) for t in texts]
                n_tokens = [int(t[-1]) for t in tables]
            else:
                n_tokens = [own.count(t) for t in texts]
            arrays = [batch.column(0), pa.array(n_bytes, pa.int64()), pa.array(n_tokens, pa.int64()), pa.array([n > limit for n in n_tokens])]
            names = ["doc_id", "n_bytes", "n_tokens", "over_limit"]
            if prefixes:
                arrays, names = [*arrays, pa.array([t.tolist() for t in tables], pa.list_(pa.int64()))], [*names, "prefix_counts"]
            yield pa.RecordBatch.from_arrays(arrays, names)

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean" + ", prefix_counts array<long>" * prefixes)


def op4_token_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts(table(spark, sf_dir, "documents"))
