"""Byte automata: a small regex grammar, subset construction and minimisation into transition arrays.

Grammar: literals, ``.`` (any byte but LF), ``\\xHH`` and escaped punctuation, ``[...]`` with ranges and ``^``, groups, ``|``, ``? * + {n} {n,} {n,m}``.
"""

from __future__ import annotations

import re

import numpy as np

ALL = frozenset(range(256))


class _Parser:
    """Thompson construction; fragments are (start, end) states of self.nfa."""

    def __init__(self):
        self.moves: list[list[tuple[frozenset, int]]] = []
        self.empty: list[list[int]] = []

    def state(self) -> int:
        self.moves.append([])
        self.empty.append([])
        return len(self.moves) - 1

    def turn(self) -> None:
        """Turn all moves round."""
        moves, empty = [[] for _ in self.moves], [[] for _ in self.empty]
        for a, here in enumerate(self.moves):
            for bytes_, b in here:
                moves[b].append((bytes_, a))
        for a, here in enumerate(self.empty):
            for b in here:
                empty[b].append(a)
        self.moves, self.empty = moves, empty

    def add(self, pattern: str) -> tuple[int, int]:
        self.p, self.i = pattern, 0
        out = self._alternatives()
        if self.i != len(pattern):
            raise ValueError(f"cannot parse {pattern!r} at {self.i}")
        return out

    def _peek(self) -> str:
        return self.p[self.i : self.i + 1]

    def _alternatives(self):
        parts = [self._sequence()]
        while self._peek() == "|":
            self.i += 1
            parts.append(self._sequence())
        if len(parts) == 1:
            return parts[0]
        a, z = self.state(), self.state()
        for s, e in parts:
            self.empty[a].append(s)
            self.empty[e].append(z)
        return a, z

    def _sequence(self):
        a = z = self.state()
        while self._peek() not in ("", "|", ")"):
            s, e = self._repeated()
            self.empty[z].append(s)
            z = e
        return a, z

    def _repeated(self):
        begin = self.i
        frag = self._atom()
        text, (low, high) = self.p[begin : self.i], (1, 1)
        if self._peek() and self._peek() in "?*+":
            low, high = {"?": (0, 1), "*": (0, None), "+": (1, None)}[self._peek()]
            self.i += 1
        elif m := re.match(r"\{(\d+)(,?)(\d*)\}", self.p[self.i :]):
            self.i += m.end()
            low = int(m[1])
            high = int(m[3]) if m[3] else None if m[2] else low
        else:
            return frag

        def again():
            keep = self.p, self.i
            self.p, self.i = text, 0
            out = self._atom()
            self.p, self.i = keep
            return out

        a = z = self.state()
        for _ in range(low):
            s, e = again()
            self.empty[z].append(s)
            z = e
        if high is None:
            s, e = again()
            self.empty[z].append(s)
            self.empty[e].append(z)
        else:
            end = self.state()
            for _ in range(high - low):
                self.empty[z].append(end)
                s, e = again()
                self.empty[z].append(s)
                z = e
            self.empty[z].append(end)
            z = end
        return a, z

    def _atom(self):
        c = self._peek()
        if c == "(":
            self.i += 1
            out = self._alternatives()
            if self._peek() != ")":
                raise ValueError(f"unclosed group in {self.p!r}")
            self.i += 1
            return out
        bytes_ = self._class() if c == "[" else ALL - {10} if c == "." else None
        if bytes_ is None:
            bytes_ = frozenset({self._char()})
        elif c == ".":
            self.i += 1
        a, z = self.state(), self.state()
        self.moves[a].append((bytes_, z))
        return a, z

    def _char(self) -> int:
        c = self._peek()
        self.i += 1
        if c == "\\":
            c = self._peek()
            self.i += 1
            if c == "x":
                self.i += 2
                return int(self.p[self.i - 2 : self.i], 16)
        if ord(c) > 127:
            raise ValueError("patterns are ASCII")
        return ord(c)

    def _class(self) -> frozenset:
        self.i += 1
        invert = self._peek() == "^"
        self.i += invert
        out: set[int] = set()
        while self._peek() != "]":
            lo = hi = self._char()
            if self._peek() == "-" and self.p[self.i + 1] != "]":
                self.i += 1
                hi = self._char()
            out.update(range(lo, hi + 1))
        self.i += 1
        return ALL - out if invert else frozenset(out)


class Automaton:
    """Minimal deterministic automaton of several rules. table[state * n_classes + class] is the next state times n_classes.

    labels[k] is the bit set of rules that accept in state k; accepting states have the largest numbers. State 0 is the start;
    with search=True every rule may begin anywhere. backward=True compiles the rules' mirror images, for a pass from a
    text's end to its start. In an anchored automaton ``dead`` is the state without return, or -1.
    """

    def __init__(self, patterns: list[str], search: bool, backward: bool = False):
        nfa = _Parser()
        spans = [nfa.add(p) for p in patterns]
        if backward:
            nfa.turn()
            spans = [(e, s) for s, e in spans]
        start = nfa.state()
        nfa.empty[start] = [s for s, _ in spans]
        ends = {e: 1 << k for k, (_, e) in enumerate(spans)}
        signature = np.zeros(256, object)
        for at, b in enumerate({b for m in nfa.moves for b, _ in m}):
            for x in b:
                signature[x] |= 1 << at
        kinds = {v: i for i, v in enumerate(dict.fromkeys(signature.tolist()))}
        self.classes = np.array([kinds[v] for v in signature.tolist()], np.uint8)
        self.n_classes = n = len(kinds)
        sample = [int(np.flatnonzero(self.classes == c)[0]) for c in range(n)]

        def closed(states) -> frozenset:
            out, todo = set(states), list(states)
            while todo:
                for t in nfa.empty[todo.pop()]:
                    if t not in out:
                        out.add(t)
                        todo.append(t)
            return frozenset(s for s in out if nfa.moves[s] or s in ends)

        step = [[[t for bs, t in m if x in bs] for x in sample] for m in nfa.moves]
        root = closed([start])
        names, rows, todo = {root: 0}, [], [root]
        while todo:
            here, nxt = todo.pop(0), []
            for c in range(n):
                to = closed({t for s in here for t in step[s][c]})
                to = to | root if search else to
                if to not in names:
                    names[to] = len(names)
                    todo.append(to)
                nxt.append(names[to])
            rows.append(nxt)
        moves = np.array(rows)
        accept = np.array([sum({ends[s] for s in st if s in ends}) for st in names], np.int64)
        part = np.unique(accept, return_inverse=True)[1].reshape(-1)
        while True:
            finer = np.unique(np.column_stack([part, part[moves]]), axis=0, return_inverse=True)[1].reshape(-1)
            if finer.max() == part.max():
                break
            part = finer
        first = np.unique(part, return_index=True)[1]
        order = np.argsort(accept[first] != 0, kind="stable")
        order = np.concatenate(([part[0]], order[order != part[0]])) if not accept[0] else order
        number = np.empty(len(order), np.int64)
        number[order] = np.arange(len(order))
        self.n_states = len(order)
        self.labels = accept[first][order]
        self.start = int(number[part[0]])
        self.first_accepting = int(np.count_nonzero(self.labels == 0))
        self.table = (number[part[moves[first[order]]]] * n).astype(np.int32).reshape(-1)
        stay = (self.table.reshape(-1, n) == (np.arange(self.n_states) * n)[:, None]).all(axis=1) & (self.labels == 0)
        self.dead = int(np.flatnonzero(stay)[0]) if stay.any() and not search else -1
        self.as_list = self.table.tolist()
        self.label_list = self.labels.tolist()

    def mark_backward(self, data: np.ndarray, offs: np.ndarray, lanes: int = 64) -> np.ndarray:
        """Bit set, for each byte, of the rules that begin there: one pass over every byte, rows side by side from their ends."""
        marks = np.zeros(len(data), np.uint16)
        size = np.diff(offs)
        order = np.argsort(-size, kind="stable")
        at, left = offs[1:][order] - 1, size[order]
        cls, n, labels = self.classes[data], self.n_classes, self.labels.astype(np.uint16)
        state = np.full(len(order), self.start * n, np.int32)
        k, p = int(np.count_nonzero(left)), 0
        ascending = left[::-1]
        while k > lanes:
            until = int(left[k - 1])
            for p in range(p, until):
                here = at[:k] - p
                s = self.table[state[:k] + cls[here]]
                state[:k] = s
                marks[here] = labels[s // n]
            p = until
            k = len(left) - int(np.searchsorted(ascending, p, "right"))
        table, bits, limit = self.as_list, self.label_list, self.first_accepting * n
        for row in range(k):
            s, end = int(state[row]), int(at[row]) - p
            begin = end - (int(left[row]) - p)
            found = np.zeros(end - begin, np.uint16)
            for i, c in enumerate(cls[begin + 1 : end + 1][::-1].tobytes()):
                s = table[s + c]
                if s >= limit:
                    found[i] = bits[s // n]
            marks[begin + 1 : end + 1] = found[::-1]
        return marks

    def longest(self, raw: bytes, begin: int) -> tuple[int, int]:
        """End and label of the longest accepted stretch from begin, or (-1, 0)."""
        table, n, limit, dead = self.as_list, self.n_classes, self.first_accepting * self.n_classes, self.dead * self.n_classes
        s, end, label = self.start * n, -1, 0
        for i in range(begin, len(raw)):
            s = table[s + raw[i]]
            if s == dead:
                break
            if s >= limit:
                end, label = i + 1, s
        return end, self.label_list[label // n] if end >= 0 else 0
