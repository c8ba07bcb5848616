"""License scan, DataFrame functions only: MinHash bands over overlapping text windows retrieve templates, exact shingle
containment verifies them.

Words are runs of a-z and 0-9 after lower-casing; shingles have five words (fewer words are one shingle). Each template
length has windows of its own: a quarter longer than the template and moved on by that quarter, so every occurrence lies
whole in some window, and a window that contains 80 % of a template has a similarity of over 0.5 with it. One min-hash
a band and BANDS bands then miss with a probability below 2**-BANDS.

Only windows around gate words are formed. Gate words are chosen from the templates so that in each template more than
a fifth of the shingles hold one: without a gate word a window cannot contain 80 % of any template.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table
from .license_texts import TEMPLATES

WORDS = 5
CONTAINMENT = 0.8
BANDS = 16

TEMPLATE_ROWS, TEMPLATE_BYTES = 500, 4 << 20  # a table of templates may have so many rows and bytes


def words_of(text: str) -> list[str]:
    return re.findall("[a-z0-9]+", text.lower())


def grams(words: list[str]) -> list[str]:
    return [" ".join(words[i : i + WORDS]) for i in range(max(1, len(words) - WORDS + 1))] if words else []


def gate_words(templates, containment: float) -> list[str]:
    """Words so that more than 1 - containment of each template's distinct shingles hold one of them; rare and long words first."""
    sets = [set(grams(words_of(t))) for _, t in templates]
    use: dict[str, int] = {}
    for _, t in templates:
        for w in set(words_of(t)):
            use[w] = use.get(w, 0) + 1
    chosen: list[str] = []
    for s in sorted(sets, key=len):
        missing = lambda: sum(not set(g.split()) & set(chosen) for g in s)  # noqa: B023, E731
        while s and missing() >= containment * len(s):
            gain = {w: sum(w in g.split() for g in s) for w in {w for g in s for w in g.split()} - set(chosen)}
            chosen.append(max(gain, key=lambda w: (min(len(w), 6), gain[w] * use[w], w)))  # noqa: B023
    return chosen


def _shingles(words: Column) -> Column:
    """Distinct shingles of an array of words."""
    last = F.greatest(F.size(words) - WORDS, F.lit(0))
    return F.array_distinct(F.transform(F.sequence(F.lit(0), last), lambda i: F.array_join(F.slice(words, i + 1, F.lit(WORDS)), " ")))


def _bands(shingles: Column) -> Column:
    hashed = F.transform(shingles, lambda s: F.xxhash64(s))
    return F.array(*[F.array_min(F.transform(hashed, lambda h: F.xxhash64(F.lit(b), h))) for b in range(BANDS)])  # noqa: B023


def template_table(spark: SparkSession, templates=TEMPLATES) -> DataFrame:
    """template, license_id, size (words), shingles, stride: built from literals, as many rows as templates."""
    rows = []
    for k, (name, text) in enumerate(templates):
        w = words_of(text)
        if w:
            rows.append(F.struct(F.lit(k).alias("template"), F.lit(name).alias("license_id"), F.lit(len(w)).alias("size"), F.array(*map(F.lit, sorted(set(grams(w))))).alias("shingles")))
    return spark.range(1, numPartitions=1).select(F.explode(F.array(*rows)).alias("t")).select("t.*")


def templates_of(templates) -> tuple[tuple[str, str], ...]:
    """(license_id, text) pairs from such pairs or from a table with these columns, whose size is checked; rows without either are left out."""
    if not isinstance(templates, DataFrame):
        return tuple(templates)
    rows = templates.select("license_id", "text").filter("license_id IS NOT NULL AND text IS NOT NULL")
    n, size = rows.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()
    if n > TEMPLATE_ROWS or size > TEMPLATE_BYTES:
        raise ValueError(f"{n} templates of {size} bytes; at most {TEMPLATE_ROWS} of {TEMPLATE_BYTES} are meant")
    return tuple(sorted(tuple(r) for r in rows.collect()))


def license_scan(spark: SparkSession, docs: DataFrame, templates=TEMPLATES, containment: float = CONTAINMENT) -> DataFrame:
    """doc_id, license_id, containment, start_word: licenses whose template's shingles stand in the text to containment or more.

    templates are (license_id, text) pairs or a table with these columns.
    One row for each doc_id and license, the best template and the earliest best window. Rows that share a doc_id are answered together. Null
    and empty texts hold nothing. Extra columns are ignored; an empty table gives no rows.
    """
    templates = templates_of(templates)
    gate = gate_words(templates, containment)
    sizes = sorted({len(words_of(t)) for _, t in templates} - {0})
    low = F.lower(F.col("text"))
    any_gate = F.lit(False)
    for w in gate:
        any_gate = any_gate | F.contains(low, F.lit(w))
    near = docs.select("doc_id", low.alias("text")).filter(any_gate)
    near = near.select("doc_id", F.filter(F.split("text", "[^a-z0-9]+"), lambda w: w != "").alias("words"))
    hits = F.filter(F.transform("words", lambda w, i: F.when(w.isin(gate), i)), lambda i: i.isNotNull())
    near = near.withColumn("hits", hits).filter(F.size("hits") > 0)
    plans = []
    for size in sizes:
        stride = max(1, size // 4)
        width = size + stride - 1
        starts = F.array_distinct(F.flatten(F.transform("hits", lambda p: F.sequence(F.greatest(F.lit(0), F.ceil((p - width + 1) / stride).cast("int")), F.floor(p / stride).cast("int")))))  # noqa: B023
        plans.append(F.transform(starts, lambda s: F.struct(F.lit(size).alias("size"), (s * stride).alias("start"), F.lit(width).alias("width"))))  # noqa: B023
    windows = near.withColumn("w", F.explode(F.flatten(F.array(*plans)))).filter(F.col("w.start") < F.size("words"))
    windows = windows.select("doc_id", "w.size", "w.start", _shingles(F.slice("words", F.col("w.start") + 1, F.col("w.width"))).alias("found"))
    stored = template_table(spark, templates)
    keys = stored.select("template", "license_id", "size", "shingles", F.posexplode(_bands(F.col("shingles"))).alias("band", "value"))
    probes = windows.select("*", F.posexplode(_bands(F.col("found"))).alias("band", "value"))
    pairs = probes.join(F.broadcast(keys), ["size", "band", "value"])  # at most BANDS rows a template
    share = F.size(F.array_intersect("found", "shingles")) / F.size("shingles")
    best = pairs.select("doc_id", "license_id", share.alias("containment"), "start").filter(F.col("containment") >= containment)
    best = best.groupBy("doc_id", "license_id").agg(F.max(F.struct("containment", -F.col("start"))).alias("b"))
    return best.select("doc_id", "license_id", "b.containment", (-F.col("b.col2")).cast("long").alias("start_word"))


def license_sql(templates=TEMPLATES, containment: float = CONTAINMENT) -> str:
    """DuckDB SQL for the scan's rows: every window of every template's width that shares a shingle with it, no retrieval before."""
    cells = []
    for name, text in templates:
        w = words_of(text)
        stride = max(1, len(w) // 4)
        cells.append(f"('{name}', {len(cells)}, {stride}, {len(w) + stride - 1}, [{', '.join(repr(g) for g in sorted(set(grams(w))))}])")
    return f"""
WITH t AS (SELECT license_id, template, stride, width, len(g) AS size, unnest(g) AS g FROM (VALUES {", ".join(cells)}) v(license_id, template, stride, width, g)),
d AS (SELECT doc_id, list_filter(string_split_regex(lower(text), '[^a-z0-9]+'), lambda w: w <> '') AS w FROM documents),
s AS (SELECT doc_id, unnest(range(len(w) - {WORDS - 1})) AS i, unnest(list_transform(range(1, len(w) - {WORDS - 2}), lambda i: {" || ' ' || ".join(f"w[i + {k}]" for k in range(WORDS))})) AS g FROM d WHERE len(w) >= {WORDS}),
m AS (SELECT doc_id, license_id, template, size, g, stride, unnest(range(greatest(0, CAST(ceil((i + {WORDS} - width) / stride) AS BIGINT)), i // stride + 1)) AS n FROM s JOIN t USING (g)),
c AS (SELECT doc_id, license_id, count(DISTINCT g) / any_value(size) AS containment, n * any_value(stride) AS start_word FROM m GROUP BY doc_id, license_id, template, n)
SELECT doc_id, license_id, containment, start_word FROM c WHERE containment >= {containment}
QUALIFY row_number() OVER (PARTITION BY doc_id, license_id ORDER BY containment DESC, start_word) = 1
"""


def op8_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan(spark, table(spark, sf_dir, "documents"))
