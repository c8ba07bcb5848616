import hashlib
import re
import time

import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st

from subsetlab.llm.automaton import Automaton
from subsetlab.llm.secret_scan import BASE_RULES, RULES, scan_texts

ASSIGN = re.compile(r"""((?:[Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd])|(?:[Pp][Aa][Ss][Ss][Ww][Dd])|(?:[Ss][Ee][Cc][Rr][Ee][Tt])|(?:[Tt][Oo][Kk][Ee][Nn])|(?:[Aa][Pp][Ii]_?[Kk][Ee][Yy]))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")


def expected(text):
    out = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= 8]
    out += [(m.start(), 1, m.end()) for m in re.finditer(r"AKIA[A-Z0-9]+", text) if len(m[0]) >= 16]
    out += [(m.start(), 2, m.end()) for m in re.finditer(r"[0-9a-f]+", text) if len(m[0]) >= 32]
    return sorted(out)


def scan(texts, rules=BASE_RULES):
    raw = [t.encode() for t in texts]
    offs = np.concatenate(([0], np.cumsum([len(r) for r in raw]))).astype(np.int64)
    return scan_texts(np.frombuffer(b"".join(raw), np.uint8), offs, rules)


PIECES = ["token", "TOKEN", "pass", "password", "passwd", "Secret", "api_key", "apikey", "=", ": ", " = ", '"', "'", "abc", "12345678", "é", "AKIA", "ABCDEFGH1234", "0123456789abcdef", "\n", "ſecret", "—", "=x"]


@settings(max_examples=150, deadline=None)
@given(st.lists(st.lists(st.sampled_from(PIECES), max_size=14).map("".join), min_size=1, max_size=6))
def test_base_spans_equal_regex(texts):
    assert scan(texts) == [expected(t) for t in texts]


def test_consumed_short_candidate():
    assert scan(["token=passwd:abcdefgh", "", "x"]) == [[], [], []]
    assert scan(["é token=password=abc12345"]) == [[(2, 0, 25)]]


def test_many_lanes_and_a_long_text():
    texts = [f"é{'x' * i} token: {'ab' * 20}" for i in range(200)] + ["word " * 40_000 + "AKIA" + "Z" * 20, ""]
    assert scan(texts) == [expected(t) for t in texts]


def test_more_rules():
    text = "-----BEGIN RSA PRIVATE KEY----- ghp_" + "G1" * 18 + " AIza" + "x" * 35
    kinds = [RULES[k].kind for _, k, _ in scan([text], RULES)[0]]
    assert kinds == ["private_key", "code_host", "cloud_key"]


def test_time_is_linear_in_one_text():
    def seconds(n):
        start = time.process_time()
        assert scan(["eyJ" * n, "eyJa." * n, "-----BEGIN " * n, "token:" * n], RULES) == [[]] * 4
        return time.process_time() - start

    seconds(1000)
    assert seconds(80_000) < 16 * max(seconds(20_000), 0.05)  # a quadratic scan takes hours here
    token = "eyJ" + "a" * 9 + ".eyJ" + "b" * 9 + "." + "c" * 9
    assert scan(["eyJ." * 50 + token], RULES) == [[(200, 7, 200 + len(token))]]


@settings(max_examples=60, deadline=None)
@given(st.lists(st.sampled_from(["a", "b", "ab", "c", "x"]), max_size=12).map("".join))
def test_marks_are_all_begins(text):
    patterns = ["a(b|c)+", "ab{2,3}c*", "[^a]b?x"]
    auto = Automaton(patterns, search=True, backward=True)
    raw = np.frombuffer(text.encode(), np.uint8)
    for lanes in (0, 64):
        marks = auto.mark_backward(raw, np.array([0, len(raw)]), lanes)
        assert marks.tolist() == [sum(1 << k for k, p in enumerate(patterns) if re.compile(p).match(text, i)) for i in range(len(text))]


def test_edge_rows_of_a_table(spark):
    from subsetlab.llm.secret_scan import secret_scan

    long = "word " * 300_000 + "token=abcdefgh1"
    rows = [(1, None, "x", 5), (2, "", "x", 5), (3, "token=abcdefgh", "x", 5), (3, "token=abcdefgh", "x", 5), (None, "AKIA" + "A" * 12, "x", 5), (4, long, "x", 5)]
    df = spark.createDataFrame(rows, "doc_id long, text string, spans string, kind int")
    got = sorted(((r.doc_id or -1, [tuple(s) for s in r.spans]) for r in secret_scan(df).collect()), key=repr)
    assert got == sorted([(1, []), (2, []), (3, [("assign", 0, 14)]), (3, [("assign", 0, 14)]), (-1, [("access", 0, 16)]), (4, [("assign", 1_500_000, 1_500_015)])], key=repr)
    empty = secret_scan(df.limit(0))
    assert empty.columns == ["doc_id", "spans"] and empty.count() == 0


@settings(max_examples=60, deadline=None)
@given(st.text(alphabet="abc", max_size=12))
def test_automaton_against_re(text):
    for p in ("a(b|c)+a?", "ab{2,3}c*", "[^a]b?", "(ab|a)(c|bc)"):
        m = re.fullmatch(p, text)
        end, label = Automaton([p], search=False).longest(bytes(Automaton([p], search=False).classes[np.frombuffer(text.encode(), np.uint8)]), 0)
        assert (end == len(text) and label == 1) == bool(m and text)


def test_query(spark, sf):
    from subsetlab.llm.secret_scan import op3_secret_scan

    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    rows = op3_secret_scan(spark, sf).collect()
    assert len(rows) == len(texts)
    for r in rows:
        e = expected(texts[r.doc_id])
        kinds = ("assign", "access", "hex")
        assert [r.n_assign, r.n_access, r.n_hex] == [sum(k == i for _, k, _ in e) for i in range(3)]
        assert r.base_sha256 == hashlib.sha256(",".join(f"{kinds[k]}:{a}:{b}" for a, k, b in e).encode()).hexdigest()
