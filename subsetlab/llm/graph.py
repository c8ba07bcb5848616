"""Connected components of an edge table by label propagation with pointer jumping."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialize


def components(spark: SparkSession, edges: DataFrame) -> DataFrame:
    """(id, comp): every id of edges (a, b) with the smallest id that it reaches. Edges without a or b are ignored.

    Each round takes the least label of all neighbours (combined before the shuffle) and then the label's own label; a
    round is written to the shared folder. Nothing but a flag comes to the driver.
    """
    edges = edges.filter("a IS NOT NULL AND b IS NOT NULL")
    both = materialize(spark, edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "edges")
    labels = materialize(spark, both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("id"), F.least("a", "m").alias("comp")), "labels")
    while True:
        near = both.join(labels.select(F.col("id").alias("b"), "comp").hint("merge"), "b").groupBy(F.col("a").alias("id")).agg(F.min("comp").alias("m"))
        lower = labels.join(near.hint("merge"), "id").select("id", F.least("comp", "m").alias("low"), F.col("comp").alias("old"))
        heads = labels.select(F.col("id").alias("low"), F.col("comp").alias("next"))
        labels = materialize(spark, lower.join(heads.hint("merge"), "low").select("id", F.least("low", "next").alias("comp"), "old"), "labels")
        if labels.filter("comp <> old").isEmpty():
            return labels.select("id", "comp")
        labels = labels.select("id", "comp")
