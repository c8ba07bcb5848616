import duckdb
import pytest
from pyspark.sql import functions as F

from subsetlab.llm.license_scan import gate_words, grams, license_scan, license_sql, op8_license_scan, words_of
from subsetlab.llm.license_texts import TEMPLATES


GPL = next(t for name, t in TEMPLATES if name == "GPL-2.0")


def brute(docs, least=0.8):
    """(doc, license) -> containment; windows as wide as the scan's."""
    out = {}
    for d, text in docs:
        words = words_of(text or "")
        for name, t in TEMPLATES:
            own, size = set(grams(words_of(t))), len(words_of(t))
            stride = max(1, size // 4)
            if not own & set(grams(words)) and len(words) >= 5:
                continue
            for s in range(0, len(words), stride):
                v = len(own & set(grams(words[s : s + size + stride - 1]))) / len(own)
                if v >= least:
                    out[d, name] = max(out.get((d, name), 0), v)
    return out


@pytest.mark.parametrize("where", ["sf0.01"])
def test_query_against_brute_force(spark, where):
    path = f"/root/testdata/{where}"
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{path}/documents.parquet").collect()]
    got = {(r.doc_id, r.license_id): r.containment for r in op8_license_scan(spark, path).collect()}
    want = brute(docs)
    assert want and got == want


def test_gate_words_cover_every_template():
    gate = set(gate_words(TEMPLATES, 0.8))
    for _, t in TEMPLATES:
        g = set(grams(words_of(t)))
        assert sum(bool(gate & set(x.split())) for x in g) > 0.2 * len(g) - 1e-9


def test_every_template_and_edge_cases(spark):
    docs = [(k, "Vorher %%% " * k + t.upper().replace(" ", " \n") + " nachher é" * 3, "x") for k, (_, t) in enumerate(TEMPLATES)]
    long = GPL.split()
    long[20] = "changed"
    docs += [(90, " ".join(long), "x"), (91, " ".join(GPL.split()[:15]), "x"), (92, None, "x"), (93, "", "x"), (94, "license " * 20_000, "x"), (None, TEMPLATES[0][1], "x")]
    df = spark.createDataFrame(docs, "doc_id long, text string, license_id string")
    got = {(r.doc_id, r.license_id): r.containment for r in license_scan(spark, df).collect()}
    assert got == {**brute([d[:2] for d in docs])}
    assert all(got[k, name] == 1 for k, (name, _) in enumerate(TEMPLATES))
    assert (90, "GPL-2.0") in got and not [1 for d, _ in got if d in (91, 92, 93, 94)]
    assert license_scan(spark, df.limit(0)).count() == 0


def test_query_equals_sql(spark):
    path = "/root/testdata/sf0.01"
    duckdb.sql(f"CREATE OR REPLACE VIEW documents AS SELECT * FROM '{path}/documents.parquet'")
    want = duckdb.sql(license_sql()).fetchall()
    assert want and sorted(want) == sorted(tuple(r) for r in op8_license_scan(spark, path).collect())


def test_templates_from_a_table_and_repeated_documents(spark):
    table = spark.createDataFrame([("MIT", TEMPLATES[3][1], 1), ("House", "All rights of the house are kept by the house.", 2), (None, "x", 3), ("y", None, 4)], "license_id string, text string, doc_id int")
    docs = spark.createDataFrame([(1, "x " * 30 + TEMPLATES[3][1]), (1, "All rights of the house are kept by the house"), (1, "nothing"), (2, TEMPLATES[3][1][:600])], "doc_id long, text string")
    got = {(r.doc_id, r.license_id): r.containment for r in license_scan(spark, docs, table).collect()}
    assert got == {(1, "MIT"): 1.0, (1, "House"): 1.0}
    with pytest.raises(ValueError):
        license_scan(spark, docs, table.select(F.explode(F.sequence(F.lit(1), F.lit(300))), "license_id", "text"))
