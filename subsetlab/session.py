"""Session builder. Foreign sessions are used as they are and never stopped."""

from __future__ import annotations

import os

from pyspark.sql import SparkSession


def get_session(app: str = "subsetlab", master: str | None = None, shuffle_partitions: int | None = None) -> SparkSession:
    active = SparkSession.getActiveSession()
    if active is not None:
        return active
    builder = SparkSession.builder.appName(app).config("spark.sql.session.timeZone", "UTC").config("spark.sql.adaptive.enabled", "true")
    builder = builder.config("spark.sql.execution.arrow.pyspark.enabled", "true").config("spark.ui.enabled", os.environ.get("SUBSETLAB_UI", "false"))
    if master:
        builder = builder.master(master)
    if shuffle_partitions:
        builder = builder.config("spark.sql.shuffle.partitions", str(shuffle_partitions))
    return builder.getOrCreate()
