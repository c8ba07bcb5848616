"""Exact dedup by skew-safe combining, DataFrame functions only.

Rows with equal whole texts (null counts as empty) form a group. Three combining steps compare full content as the
grouping key: inside each task before any exchange (partial aggregation), in salted digest groups, and over the salt
winners of a digest. A hot group leaves a task as one row, a salt group as one row, so no task sees its members.
Members then find their group by digest, hot digests by a broadcast of bounded size; should different texts ever share
one, those members are matched by text.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import join_group, materialize, small_side, table, tidy

SALTS = 16


def sha256_text(text: Column) -> Column:
    return F.sha2(text, 256)


def content_groups(docs: DataFrame, salts: int = SALTS, digest=sha256_text) -> DataFrame:
    """(digest, text, keep_id, group_size): one row for each distinct text; keep_id is its largest doc_id."""
    rows = docs.select(F.col("doc_id").alias("id"), F.coalesce("text", F.lit("")).alias("text"))
    rows = rows.withColumn("digest", digest(F.col("text"))).withColumn("salt", F.pmod(F.xxhash64("id"), F.lit(salts)))
    salted = rows.groupBy("digest", "salt", "text").agg(F.max("id").alias("id"), F.count(F.lit(1)).alias("n"))
    return salted.groupBy("digest", "text").agg(F.max("id").alias("keep_id"), F.sum("n").alias("group_size"))


@tidy
def exact_dedup(spark: SparkSession, docs: DataFrame, salts: int = SALTS, digest=sha256_text) -> DataFrame:
    """One row per input row: doc_id, keep_id, group_size, kept, text_digest.

    Null and empty texts are equal. Rows that repeat a doc_id with the same text are all kept or all dropped with it
    (the id stays, group_size counts the rows). A null doc_id never wins over a number; a group of null ids only has keep_id null and
    kept true. An empty table gives no rows; extra columns are ignored.
    """
    groups = content_groups(docs, salts, digest)
    by_digest = groups.groupBy("digest").agg(F.count(F.lit(1)).alias("n_texts"), F.max("keep_id").alias("keep_id"), F.sum("group_size").alias("group_size"))
    by_digest = materialize(spark, by_digest, "exact-groups")
    members = docs.select("doc_id", digest(F.coalesce("text", F.lit(""))).alias("digest"))
    found = join_group(members, by_digest, "digest", "group_size", "doc_id").filter("n_texts = 1").select("doc_id", "keep_id", "group_size", "digest")
    shared = by_digest.filter("n_texts > 1").select("digest")
    if not shared.isEmpty():  # different texts under one digest: only those rows are matched by content
        inner = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).withColumn("digest", digest(F.col("text")))
        exact = inner.join(shared, "digest", "left_semi").join(groups.join(shared, "digest", "left_semi"), ["digest", "text"])
        found = found.unionByName(exact.select("doc_id", "keep_id", "group_size", "digest"))
    kept = F.coalesce(F.col("doc_id") == F.col("keep_id"), F.col("keep_id").isNull())
    return found.select("doc_id", "keep_id", "group_size", kept.alias("kept"), F.col("digest").alias("text_digest"))


@tidy
def drop_exact_copies(spark: SparkSession, docs: DataFrame, salts: int = SALTS) -> DataFrame:
    """docs without the rows whose text also stands in a row of larger doc_id; columns unchanged.

    A doc_id that repeats with the same text leaves all its rows; ids are unique in the tables this runs on.
    """
    loses = exact_dedup(spark, docs, salts).filter(~F.col("kept")).select("doc_id", "text_digest").distinct()
    loses = materialize(spark, loses, "exact-copies")
    same = (docs["doc_id"].eqNullSafe(loses["doc_id"])) & (sha256_text(F.coalesce(docs["text"], F.lit(""))) == loses["text_digest"])
    return docs.join(small_side(loses, 500_000), same, "left_anti").select(*docs.columns)


def op5_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup(spark, table(spark, sf_dir, "documents")).withColumnRenamed("text_digest", "text_sha256")


OP5_SQL = """
SELECT doc_id, max(doc_id) OVER (PARTITION BY t) AS keep_id, count(*) OVER (PARTITION BY t) AS group_size,
       doc_id = max(doc_id) OVER (PARTITION BY t) AS kept, sha256(t) AS text_sha256
FROM (SELECT doc_id, coalesce(text, '') AS t FROM documents)
"""
