"""Streaming forms: windows over events, filter and assignment with frozen models, bounded per-cluster top-q state.

A rank cut is undefined on an unbounded stream, so stage I uses a threshold that was learnt on a batch, and stage II a
saved centroid model.
"""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.udf import byte_entropy
from ..operators.assign import assign_clusters
from ..operators.centroids import CentroidModel
from ..operators.select import top_q_per_group


def type_entropy(events: DataFrame, window, kinds: list[str], late: str = "1 day") -> DataFrame:
    """(start, user_id, n, entropy) of the event types in a window; the kinds are the levels."""
    cols = [F.count_if(F.col("event_type") == k).alias(f"n{i}") for i, k in enumerate(kinds)]
    grouped = events.withWatermark("ts", late).groupBy(window.alias("w"), "user_id").agg(*cols, F.count(F.lit(1)).alias("n"))
    total = F.col("n").cast("double")
    parts = [F.when(F.col(f"n{i}") > 0, F.col(f"n{i}") * F.ln(F.col(f"n{i}").cast("double"))).otherwise(0.0) for i in range(len(kinds))]
    h = F.greatest(F.lit(0.0), F.ln(total) - sum(parts[1:], parts[0]) / total)
    return grouped.select(F.col("w.start").alias("start"), "user_id", "n", h.alias("entropy"))


def sessions(events: DataFrame, gap: str, late: str = "1 day") -> DataFrame:
    """(start, stop, user_id, n)"""
    grouped = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return grouped.select(F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "user_id", "n")


def deduplicated(events: DataFrame, keys: list[str], late: str = "1 day") -> DataFrame:
    """First row of each key within the watermark; state is dropped behind it."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def filter_assign(samples: DataFrame, encode: Callable[[DataFrame], DataFrame], tau: float, model: CentroidModel) -> DataFrame:
    """(sample_id, cluster_id, sim) of the samples with entropy of at least tau; row-local, so batch and stream share it."""
    return assign_clusters(encode(samples.filter(byte_entropy("payload") >= tau)), model)


def top_q_sink(store: Callable[[DataFrame], None], load: Callable[[], DataFrame | None], q: int) -> Callable[[DataFrame, int], None]:
    """foreachBatch function that merges a micro-batch into the stored q best rows of each cluster; re-running a batch changes nothing."""

    def merge(batch: DataFrame, _: int) -> None:
        held = load()
        rows = batch.filter("cluster_id IS NOT NULL").withColumn("_s", F.round("sim", 9))
        both = rows if held is None else rows.unionByName(held).dropDuplicates(["sample_id"])
        store(top_q_per_group(both, "cluster_id", q, "_s", "sample_id"))

    return merge


def top_q_stateful(assigned: DataFrame, q: int) -> DataFrame:
    """(cluster_id, sample_id, sim, batch_rows): state of each cluster's q best rows; the bounded list is emitted at every change."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def step(key: tuple, batches, state: GroupState):
        held = list(zip(*state.get, strict=True)) if state.exists else []
        for pdf in batches:
            held += [(-round(s, 9), int(i)) for s, i in zip(pdf["sim"], pdf["sample_id"], strict=True)]
        held = sorted(set(held))[:q]
        state.update(([s for s, _ in held], [i for _, i in held]))
        yield pd.DataFrame({"cluster_id": [key[0]] * len(held), "sample_id": [i for _, i in held], "sim": [-s for s, _ in held]})

    rows = assigned.filter("cluster_id IS NOT NULL")
    return rows.groupBy("cluster_id").applyInPandasWithState(step, "cluster_id int, sample_id long, sim double", "best array<double>, ids array<long>", "update", GroupStateTimeout.NoTimeout)


def drain(query_frame: DataFrame, path: str, mode: str = "append") -> None:
    """Run a stream over what is there now into Parquet at path, with its checkpoint beside it."""
    writer = query_frame.writeStream.outputMode(mode).option("checkpointLocation", f"{path}-checkpoint").trigger(availableNow=True)
    writer.format("parquet").option("path", path).start().awaitTermination()


def drain_batches(query_frame: DataFrame, path: str, fn: Callable[[DataFrame, int], None], mode: str = "append") -> None:
    query_frame.writeStream.outputMode(mode).option("checkpointLocation", f"{path}-checkpoint").trigger(availableNow=True).foreachBatch(fn).start().awaitTermination()
