"""Secret scan with one combined deterministic automaton.

All rules are compiled together (subset construction, minimisation) into one transition array. It holds their mirror
images: a single pass over every byte, from a text's end to its start, marks each position where a match of a rule
begins. From the leftmost mark of a kind its longest match is read off forwards, the next one is looked for behind it, and
matches that break the rule's length condition are dropped. No byte is read again for a match that does not exist, so
the time is linear in the text for rules whose matches end where they can no longer be extended, as all of these do.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .automaton import Automaton
from .common import doc_blocks, released, table, text_buffer

SCAN_BYTES = 1 << 22  # whole texts of about so many bytes are marked together


@dataclass(frozen=True)
class Rule:
    """match: a candidate span; valid: the spans that count (match with its length condition).

    Of a frequent rule's candidates hardly any counts, as in prose; its valid form is compiled into the combined automaton too, and
    only texts where that begins somewhere are looked through.
    """

    kind: str
    match: str
    valid: str
    frequent: bool = False


def _either(word: str) -> str:
    return "".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in word)


_NAMES = "(" + "|".join(map(_either, ("password", "passwd", "secret", "token"))) + "|" + _either("api") + "_?" + _either("key") + ")"
_SIGN = _NAMES + "[\"']?\\x20*[:=]\\x20*[\"']?"
_VALUE = "[A-Za-z0-9+/_.=-]"
BASE_RULES = (
    Rule("assign", _SIGN + _VALUE + "+", _SIGN + _VALUE + "{8,}"),
    Rule("access", "AKIA[A-Z0-9]+", "AKIA[A-Z0-9]{12,}"),
    Rule("hex", "[0-9a-f]+", "[0-9a-f]{32,}", frequent=True),
)
MORE_RULES = (
    Rule("private_key", "-----BEGIN [A-Z0-9 ]*PRIVATE KEY-----", "-----BEGIN [A-Z0-9 ]*PRIVATE KEY-----"),
    Rule("code_host", "gh[pousr]_[A-Za-z0-9]+", "gh[pousr]_[A-Za-z0-9]{36,}"),
    Rule("cloud_key", "AIza[0-9A-Za-z_-]+", "AIza[0-9A-Za-z_-]{35,}"),
    Rule("chat", "xox[abprs]-[0-9A-Za-z-]+", "xox[abprs]-[0-9A-Za-z-]{10,}"),
    Rule("web_token", "eyJ[A-Za-z0-9_-]+\\.eyJ[A-Za-z0-9_-]+\\.[A-Za-z0-9_-]+", "eyJ[A-Za-z0-9_-]{8,}\\.eyJ[A-Za-z0-9_-]{8,}\\.[A-Za-z0-9_-]{8,}"),
)
RULES = BASE_RULES + MORE_RULES


@dataclass
class Scanner:
    """marker: all rules' combined automaton; gates: for each rule the bit that a text must hold; extents: a rule's own match and valid form, anchored."""

    marker: Automaton
    gates: list[int]
    extents: list[Automaton]


@cache
def compiled(rules: tuple[Rule, ...] = RULES) -> Scanner:
    often = [k for k, r in enumerate(rules) if r.frequent]
    if len(rules) + len(often) > 16:
        raise ValueError("at most 16 rules, frequent ones counting twice")
    marker = Automaton([r.match for r in rules] + [rules[k].valid for k in often], search=True, backward=True)
    gates = [1 << (len(rules) + often.index(k) if r.frequent else k) for k, r in enumerate(rules)]
    return Scanner(marker, gates, [Automaton([r.match, r.valid], search=False) for r in rules])


def spans_of(raw: bytes, starts: list[int], rule: Automaton) -> list[tuple[int, int]]:
    """Valid byte spans from the positions where a match begins: leftmost, longest, non-overlapping; a match that is too short still uses up its bytes."""
    out, after = [], 0
    for at in starts:
        if at < after:
            continue
        after, label = rule.longest(raw, at)
        if label & 2:
            out.append((at, after))
    return out


def scan_texts(data: np.ndarray, offs: np.ndarray, rules: tuple[Rule, ...] = RULES, scanner: Scanner | None = None) -> list[list[tuple[int, int, int]]]:
    """For each row its valid spans (start, rule number, end) in code points, sorted."""
    scanner = scanner or compiled(rules)
    out: list[list[tuple[int, int, int]]] = [[] for _ in range(len(offs) - 1)]
    for i, j in doc_blocks(offs, SCAN_BYTES):
        part, at = data[offs[i] : offs[j]], offs[i : j + 1] - offs[i]
        marks = scanner.marker.mark_backward(part, at)
        found: dict[int, list[tuple[int, int, int]]] = {}
        for k, (gate, rule) in enumerate(zip(scanner.gates, scanner.extents, strict=True)):
            rows = np.unique(np.searchsorted(at, np.flatnonzero(marks & gate), "right") - 1)
            for row in rows.tolist():
                a, b = at[row], at[row + 1]
                starts = np.flatnonzero(marks[a:b] & (1 << k)).tolist()
                spans = spans_of(rule.classes[part[a:b]].tobytes(), starts, rule)
                found.setdefault(row, []).extend((s, k, e) for s, e in spans)
        for row, spans in found.items():
            points = np.concatenate(([0], np.cumsum((part[at[row] : at[row + 1]] & 0xC0) != 0x80)))
            out[i + row] = sorted((int(points[s]), k, int(points[e])) for s, k, e in spans)
    return out


def secret_scan(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """doc_id, spans: array of (kind, start, end) in code points, end exclusive, sorted by start and then by rule.

    Null and empty texts have no spans. One output row per input row, repeated ids included; other columns are ignored.
    """

    scanner = compiled(rules)  # once, on the driver; a few thousand numbers

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))
        for batch in released(batches):
            found = scan_texts(*text_buffer(batch.column(1)), rules, scanner)
            rows = [[{"kind": rules[k].kind, "start": a, "end": b} for a, k, b in spans] for spans in found]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rows, kind)], ["doc_id", "spans"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, spans array<struct<kind string, start long, end long>>")


def op3_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    base = {r.kind for r in BASE_RULES}

    def digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in released(batches):
            cols = {n: [] for n in ("n_assign", "n_access", "n_hex", "base_sha256", "spans")}
            for spans in batch.column(1).to_pylist():
                text = lambda keep: ",".join(f"{s['kind']}:{s['start']}:{s['end']}" for s in spans if keep(s["kind"]))
                for kind in base:
                    cols[f"n_{kind}"].append(sum(s["kind"] == kind for s in spans))
                cols["base_sha256"].append(hashlib.sha256(text(base.__contains__).encode()).hexdigest())
                cols["spans"].append(text(lambda _: True))
            yield pa.RecordBatch.from_arrays([batch.column(0)] + [pa.array(v, pa.int64() if n[0] == "n" else pa.string()) for n, v in cols.items()], ["doc_id", *cols])

    out = "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string"
    return secret_scan(table(spark, sf_dir, "documents")).mapInArrow(digest, out)
