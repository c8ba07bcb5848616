"""Corpus pipeline: quality, exact dedup, near dedup, benchmark decontamination, packing.

Every stage takes (spark, docs, sf_dir) and gives the rows that the next one works on; all but the last keep the columns
of documents. What a stage rejects is gone for the later ones.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from subsetlab.llm.common import keep_read, made_so_far, materialize, table
from subsetlab.llm.decontaminate import drop_contaminated
from subsetlab.llm.exact_dedup import drop_exact_copies
from subsetlab.llm.near_dedup import drop_near_copies
from subsetlab.llm.packing import pack_documents
from subsetlab.llm.quality import keep_good


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose line-field score reaches the threshold."""
    return keep_good(spark, docs, table(spark, sf_dir, "labels"))


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the one of largest doc_id."""
    return drop_exact_copies(spark, docs)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each component of near copies (five-word shingles, similarity 0.8) the smallest doc_id."""
    return drop_near_copies(spark, docs, k=5, percent=80)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item."""
    return drop_contaminated(spark, docs, table(spark, sf_dir, "benchmark"))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces placed into sequences."""
    return pack_documents(spark, docs)


STAGES = [
    ("quality", quality),
    ("exact_dedup", exact),
    ("near_dedup", near),
    ("decontamination", decontaminate),
    ("packing", packing),
]
ORACLE_SQL = None  # a trained line field, confirmed links and tokenizer ids have no SQL form


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Apply the stages to documents.

    Each result is a table in the shared folder; the tables behind it are deleted once the next one is written. The last
    one stays until cleanup() in subsetlab.llm.common deletes it.
    """
    docs, since = table(spark, sf_dir, "documents"), made_so_far()
    for name, stage in STAGES:
        docs = materialize(spark, stage(spark, docs, sf_dir), f"stage-{name}")
        keep_read(spark, since, docs)
    return docs
