"""Exact ids of a lower-casing word BPE for many texts at once.

Blank-delimited stretches are hashed with numpy and looked up in a per-worker table; new stretches are cut into words
and merged together, vectorised over words. Texts outside the plain range (other scripts, control characters, special
token strings) go through the library whole.
"""

from __future__ import annotations

import json
from functools import cache

import numpy as np
import regex

from .kernels import SECOND, ranges, span_hashes, word_spans

_PLAIN = regex.compile("[^\t\n\x0b\x0c\r\x20-\x7e¡-ÿ]|<\\|")
_WORDS = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|\p{L}+|\p{N}|[^\s\p{L}\p{N}]+")
TABLE_ENTRIES = 1_200_000  # stretches, in arrays
WORD_ENTRIES = 100_000  # words, in a dictionary
NONE = np.int32(2**31 - 1)


def _byte_symbols() -> list[str]:
    """Printable stand-in of every byte: printable Latin-1 stands for itself, the others follow from 256 on."""
    own = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    rest = iter(range(256, 512))
    return [chr(b) if b in own else chr(next(rest)) for b in range(256)]


class WordBpe:
    def __init__(self, path: str, table_entries: int = TABLE_ENTRIES):
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            model = json.load(f)["model"]
        vocab, suffix = model["vocab"], model["end_of_word_suffix"]
        symbols = _byte_symbols()
        self.inner = np.array([vocab[s] for s in symbols], np.int32)
        self.final = np.array([vocab[s + suffix] for s in symbols], np.int32)
        merges = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
        keys = np.array([vocab[a] << 16 | vocab[b] for a, b in merges], np.int64)
        order = np.argsort(keys)
        self.keys, self.ranks = keys[order], np.arange(len(keys), dtype=np.int32)[order]
        self.merged = np.array([vocab[a + b] for a, b in merges], np.int32)
        self.limit = table_entries
        self.words: dict[str, np.ndarray] = {}
        self._reset()

    def _reset(self) -> None:
        self.hashes, self.prints = np.zeros(0, np.uint64), np.zeros(0, np.uint64)
        self.at, self.size = np.zeros(0, np.int64), np.zeros(0, np.int64)
        self.flat = np.zeros(0, np.int32)

    def _rank(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        key = a.astype(np.int64) << 16 | b
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where((self.keys[at] == key) & (a >= 0) & (b >= 0), self.ranks[at], NONE)

    def merge_words(self, words: list[str]) -> list[np.ndarray]:
        """Ids of single words (as the library splits them), merged side by side in groups of like length."""
        raw = [w.encode() for w in words]
        out: list[np.ndarray] = [None] * len(words)
        size = np.array([len(r) for r in raw])
        for low, high in ((1, 8), (9, 12), (13, 18), (19, 32), (33, 64)):
            group = np.flatnonzero((size >= low) & (size <= high))
            if not len(group):
                continue
            n, width = size[group], high
            sym = np.full((len(group), width + 1), -1, np.int32)
            cells = np.arange(width + 1) < n[:, None]
            sym[cells] = self.inner[np.frombuffer(b"".join(raw[g] for g in group), np.uint8)]
            last = np.array([raw[g][-1] for g in group], np.uint8)
            sym[np.arange(len(group)), n - 1] = self.final[last]
            rank = self._rank(sym[:, :-1].ravel(), sym[:, 1:].ravel()).reshape(len(group), width)
            live = np.arange(len(group))
            cols = np.arange(width)
            s, r = sym, rank
            while len(live):
                pos = r.argmin(axis=1)
                best = r[np.arange(len(live)), pos]
                go = best < NONE
                if not go.all():
                    sym[live[~go]] = s[~go]
                    live, s, r, pos, best = live[go], s[go], r[go], pos[go], best[go]
                    if not len(live):
                        break
                row = np.arange(len(live))
                s[row, pos] = self.merged[best]
                shift = cols[None, :] + (cols[None, :] > pos[:, None])
                s[:, :width] = np.take_along_axis(s, shift, 1)
                s[:, width] = -1
                shift = np.minimum(cols[None, :] + (cols[None, :] >= pos[:, None]), width - 1)
                r = np.take_along_axis(r, shift, 1)
                r[:, width - 1] = NONE
                r[row, pos] = self._rank(s[row, pos], s[row, pos + 1])
                left = np.maximum(pos - 1, 0)
                r[row, left] = np.where(pos > 0, self._rank(s[row, left], s[row, pos]), r[row, left])
            counts = (sym >= 0).sum(1)
            for g, c, ids in zip(group.tolist(), counts.tolist(), sym, strict=True):
                out[g] = ids[:c].copy()
        for g in np.flatnonzero(size > 64).tolist():
            out[g] = np.array(self.library.encode(words[g], add_special_tokens=False).ids, np.int32)
        return out

    def _learn(self, stretches: list[str], hashes: np.ndarray, prints: np.ndarray) -> None:
        cut = [_WORDS.findall(s) for s in stretches]
        new = list({w for ws in cut for w in ws} - self.words.keys())
        if len(self.words) + len(new) > min(WORD_ENTRIES, self.limit):
            self.words.clear()
            new = list({w for ws in cut for w in ws})
        self.words.update(zip(new, self.merge_words(new), strict=True))
        known = self.words
        ids = [np.concatenate([known[w] for w in ws]) if len(ws) > 1 else known[ws[0]] for ws in cut]
        size = np.array([len(i) for i in ids], np.int64)
        at = len(self.flat) + np.cumsum(size) - size
        self.flat = np.concatenate([self.flat, *ids])
        to = np.searchsorted(self.hashes, hashes)  # hashes come sorted
        self.hashes, self.prints = np.insert(self.hashes, to, hashes), np.insert(self.prints, to, prints)
        self.at, self.size = np.insert(self.at, to, at), np.insert(self.size, to, size)

    def _find(self, h: np.ndarray, p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if not len(self.hashes):
            return np.zeros(len(h), np.int64), np.zeros(len(h), bool)
        at = np.minimum(np.searchsorted(self.hashes, h), len(self.hashes) - 1)
        return at, (self.hashes[at] == h) & (self.prints[at] == p)

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        """Ids (int32) of every text, without special tokens."""
        out: list[np.ndarray] = [None] * len(texts)
        odd = [i for i, t in enumerate(texts) if _PLAIN.search(t)]
        for i, e in zip(odd, self.library.encode_batch_fast([texts[i] for i in odd], add_special_tokens=False), strict=True):
            out[i] = np.array(e.ids, np.int32)
        plain = [i for i in range(len(texts)) if out[i] is None]
        raw = [texts[i].lower().encode() for i in plain]
        offs = np.concatenate(([0], np.cumsum([len(r) for r in raw]))).astype(np.int64)
        data = np.frombuffer(b"".join(raw), np.uint8)
        starts, ends, first = word_spans(data, offs)
        if len(starts):
            h = span_hashes(data, starts, ends)
            kinds, one, back = np.unique(h, return_index=True, return_inverse=True)
            p = span_hashes(data, starts[one], ends[one], SECOND)
            at, known = self._find(kinds, p)
            if not known.all():
                if len(self.hashes) + np.count_nonzero(~known) > self.limit:  # learn all stretches of these texts anew
                    self._reset()
                    known[:] = False
                miss = np.flatnonzero(~known)
                joined = data.tobytes()
                self._learn([joined[a:b].decode() for a, b in zip(starts[one[miss]].tolist(), ends[one[miss]].tolist(), strict=True)], kinds[miss], p[miss])
                at, known = self._find(kinds, p)
                if not known.all():
                    raise ValueError("stretches are still unknown after learning")
            at = at[back]
            size = self.size[at]
            ids = self.flat[ranges(self.at[at], size)]
            edge = np.concatenate(([0], np.cumsum(size)))[first]
        else:
            ids, edge = np.zeros(0, np.int32), np.zeros(len(plain) + 1, np.int64)
        for k, i in enumerate(plain):
            out[i] = ids[edge[k] : edge[k + 1]]
        if len(self.hashes) > self.limit:  # a table for these texts only
            self._reset()
        return out


@cache
def word_bpe(path: str) -> WordBpe:
    return WordBpe(path)
