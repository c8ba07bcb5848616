"""The fixtures that the queries run on."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import features
from ..operators.entropy import sample_entropy
from ..schemas import DOCUMENTS, EMBEDDINGS, VECTOR
from ..sources.tables import load_samples, table

K_E, K_D, ITERS = 20, 16, 5
BANK_LABELS = [(0, 1), (2, 3), (4, 5), (6, 7), (8, 9)]


def e_all(spark: SparkSession, d: str) -> DataFrame:
    """(sample_id, vec, label) of embeddings."""
    return table(spark, d, "embeddings").select(F.col("vec_id").alias("sample_id"), F.transform("embedding", lambda x: x.cast("double")).alias("vec"), "label")


def e_ref(spark: SparkSession, d: str) -> DataFrame:
    return e_all(spark, d).filter("sample_id % 5 < 2")


def e_pool(spark: SparkSession, d: str) -> DataFrame:
    return e_all(spark, d).filter("sample_id % 5 >= 2")


def e_scores(spark: SparkSession, d: str) -> DataFrame:
    return sample_entropy(load_samples(spark, d, EMBEDDINGS), VECTOR)


def bank(spark: SparkSession, d: str, labels: tuple[int, ...]) -> DataFrame:
    return e_ref(spark, d).filter(F.col("label").isin(*labels)).withColumnRenamed("label", "class_label")


def e_test(spark: SparkSession, d: str, n: int = 50) -> DataFrame:
    """The n rows of highest entropy in a hash slice of the pool."""
    return held_out(e_pool(spark, d), e_scores(spark, d), n)


def held_out(pool: DataFrame, scores: DataFrame, n: int = 50) -> DataFrame:
    rows = pool.join(scores, "sample_id").filter(F.conv(F.substring(F.md5(F.col("sample_id").cast("string")), 1, 8), 16, 10).cast("long") % 3 == 0)
    return rows.orderBy(F.round("entropy", 9).desc(), "sample_id").limit(n).select("sample_id", "vec", "label")


def e_candidates(spark: SparkSession, d: str, n: int = 50) -> DataFrame:
    """The pool without the held-out rows."""
    return e_pool(spark, d).join(F.broadcast(e_test(spark, d, n).select("sample_id")), "sample_id", "left_anti")  # n rows


def d_rows(spark: SparkSession, d: str) -> DataFrame:
    """(sample_id, vec, label) of documents that have a vector; the class is the language."""
    vectors = features.hashed_tokens(docs(spark, d)).filter("vec IS NOT NULL")
    return vectors.join(table(spark, d, "documents").select(F.col("doc_id").alias("sample_id"), F.col("lang").alias("label")), "sample_id")


def docs(spark: SparkSession, d: str) -> DataFrame:
    return load_samples(spark, d, DOCUMENTS)


def curated_ids(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "labels").filter("quality = 1 AND toxic = 0").select(F.col("doc_id").alias("sample_id"))


def d_ref(spark: SparkSession, d: str) -> DataFrame:
    """(sample_id, vec) of expert-curated documents."""
    return features.hashed_tokens(docs(spark, d).join(curated_ids(spark, d), "sample_id", "left_semi"))


def d_pool_samples(spark: SparkSession, d: str) -> DataFrame:
    """Documents without any label."""
    return docs(spark, d).join(table(spark, d, "labels").select(F.col("doc_id").alias("sample_id")), "sample_id", "left_anti")


def d_pool(spark: SparkSession, d: str) -> DataFrame:
    return features.hashed_tokens(d_pool_samples(spark, d))
