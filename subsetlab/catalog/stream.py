"""Streams drained into a sink and read back, and Arrow functions against their SQL forms."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F
from pyspark.sql import types as Ty

from ..functions import udf
from ..operators import features
from ..sources.tables import register_views, table, work_dir
from ..streaming import streams as ST
from . import sqlparts as P
from .core import D_MODEL, d_model, r6
from .inputs import d_pool_samples, docs
from .registry import Registry

R = Registry()
EVENTS = Ty.StructType([Ty.StructField("event_id", Ty.LongType()), Ty.StructField("ts", Ty.TimestampNTZType()), Ty.StructField("user_id", Ty.LongType()), Ty.StructField("event_type", Ty.StringType()), Ty.StructField("value", Ty.DoubleType()), Ty.StructField("props", Ty.StringType())])


def _path(spark, name):
    return f"{work_dir(spark)}/{name}-{uuid.uuid4().hex[:12]}"


def events(spark, d):
    """The events table as a stream: its rows in a folder of files by day, read file by file."""
    path = _path(spark, "events")
    table(spark, d, "events").withColumn("day", F.to_date("ts")).repartitionByRange(8, "ts").drop("day").write.parquet(path)
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", 4).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def drained(spark, frame, name, mode="append"):
    path = _path(spark, name)
    ST.drain(frame, path, mode)
    return spark.read.parquet(path)


def complete(spark, frame):
    """Drain an aggregation in complete mode through foreachBatch; the last batch is the result."""
    path = _path(spark, "complete")
    ST.drain_batches(frame, path, lambda df, _: df.write.mode("overwrite").parquet(path), "complete")
    return spark.read.parquet(path)


def _kinds(spark, d):
    return [r[0] for r in table(spark, d, "events").select("event_type").distinct().orderBy("event_type").collect()]


@R.add("st_tumbling_entropy", P.with_("x AS (SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, user_id, event_type, CAST(count(*) AS DOUBLE) AS n FROM events GROUP BY ALL)", select="SELECT CAST(epoch_us(start) AS BIGINT) AS start_us, user_id, CAST(sum(n) AS BIGINT) AS n, round(greatest(0.0, ln(sum(n)) - sum(n * ln(n)) / sum(n)), 6) AS entropy FROM x GROUP BY 1, 2"))
def _(spark, d):
    out = complete(spark, ST.type_entropy(events(spark, d), F.window("ts", "1 day"), _kinds(spark, d)))
    return r6(out.select(F.unix_micros("start").alias("start_us"), "user_id", "n", "entropy"), "entropy")


@R.add("st_sliding", P.with_("w AS (SELECT time_bucket(INTERVAL 12 HOUR, ts) - INTERVAL 12 HOUR * k AS start, user_id, event_type FROM events CROSS JOIN (SELECT unnest([0, 1]) AS k))", "x AS (SELECT start, user_id, event_type, CAST(count(*) AS DOUBLE) AS n FROM w GROUP BY ALL)", select="SELECT CAST(epoch_us(start) AS BIGINT) AS start_us, user_id, CAST(sum(n) AS BIGINT) AS n, round(greatest(0.0, ln(sum(n)) - sum(n * ln(n)) / sum(n)), 6) AS entropy FROM x GROUP BY 1, 2"))
def _(spark, d):
    out = complete(spark, ST.type_entropy(events(spark, d), F.window("ts", "1 day", "12 hours"), _kinds(spark, d)))
    return r6(out.select(F.unix_micros("start").alias("start_us"), "user_id", "n", "entropy"), "entropy")


@R.add("st_session", "SELECT user_id, CAST(epoch_us(min(ts)) AS BIGINT) AS start_us, count(*) AS n FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, session")
def _(spark, d):
    out = complete(spark, ST.sessions(events(spark, d), "6 hours"))
    return out.select("user_id", F.unix_micros("start").alias("start_us"), "n")


@R.add("st_dedup", "SELECT event_id FROM events")
def _(spark, d):
    twice = events(spark, d)
    twice = twice.withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1)))).drop("copy")
    return drained(spark, ST.deduplicated(twice, ["event_id"], "40 days"), "dedup").select("event_id")


def _doc_stream(spark, d):
    path = _path(spark, "docs")
    src = d_pool_samples(spark, d).select("sample_id", "payload")
    src.repartition(6, "sample_id").write.parquet(path)
    return spark.readStream.schema(src.schema).option("maxFilesPerTrigger", 2).parquet(path)


_FA = (*D_MODEL, P.DOC_H, P.assign("a", "(SELECT dpool.* FROM dpool JOIN dh USING (id) WHERE h >= 2.8)", "m_c"))


@R.add("st_filter_assign", P.with_(*_FA, select="SELECT id AS sample_id, k AS cluster_id, round(sim, 6) AS sim FROM a"))
def _(spark, d):
    out = drained(spark, ST.filter_assign(_doc_stream(spark, d), features.hashed_tokens, 2.8, d_model(spark, d)), "assigned")
    return r6(out, "sim")


_TOP5 = "SELECT id AS sample_id, k AS cluster_id, round(sim, 6) AS sim FROM (SELECT *, row_number() OVER (PARTITION BY k ORDER BY round(sim, 9) DESC, id) AS rk FROM a) WHERE rk <= 5"


@R.add("st_top_q_state", P.with_(*_FA, select=_TOP5))
def _(spark, d):
    path, version = _path(spark, "top"), [None]

    def load():
        return None if version[0] is None else spark.read.parquet(version[0])

    def store(df):
        new = f"{path}/{uuid.uuid4().hex[:8]}"
        df.write.parquet(new)
        version[0] = new

    ST.drain_batches(ST.filter_assign(_doc_stream(spark, d), features.hashed_tokens, 2.8, d_model(spark, d)), path, ST.top_q_sink(store, load, 5))
    return r6(load().select("sample_id", "cluster_id", "sim"), "sim")


@R.add("st_top_q_stateful", P.with_(*_FA, select=_TOP5))
def _(spark, d):
    path = _path(spark, "stateful")
    found = ST.top_q_stateful(ST.filter_assign(_doc_stream(spark, d), features.hashed_tokens, 2.8, d_model(spark, d)), 5)
    ST.drain_batches(found, path, lambda df, i: df.withColumn("batch", F.lit(i)).write.mode("append").parquet(path), "update")
    rows = spark.read.parquet(path)
    last = rows.groupBy("cluster_id").agg(F.max("batch").alias("batch"))
    return r6(rows.join(last, ["cluster_id", "batch"]).select("sample_id", "cluster_id", "sim"), "sim")


# Functions


@R.add("ud_entropy_arrow", P.with_(P.DOC_H, select="SELECT id AS sample_id, round(h, 6) AS entropy FROM dh"))
def _(spark, d):
    return docs(spark, d).select("sample_id", F.round(udf.byte_entropy("payload"), 6).alias("entropy"))


@R.add("ud_entropy_udaf", P.with_(P.level_h("h", "events", "user_id", "event_type"), select="SELECT user_id, round(h, 6) AS entropy FROM h"))
def _(spark, d):
    return table(spark, d, "events").groupBy("user_id").agg(F.round(udf.entropy_of_group("event_type"), 6).alias("entropy"))


@R.add("ud_levels_udtf", "SELECT item_id, CAST(('0x' || lv) AS INTEGER) AS level, count(*) AS n FROM (SELECT item_id, unnest(regexp_extract_all(hex(encode(text)), '..')) AS lv FROM benchmark) GROUP BY ALL")
def _(spark, d):
    udf.register(spark)
    register_views(spark, d, ["benchmark"])
    return spark.sql("SELECT item_id, level, n FROM benchmark, LATERAL sl_levels(text)")


@R.add("ud_sql_functions", P.with_(P.E, P.Z, P.DOC_H, select="SELECT dh.id AS sample_id, round(h, 6) AS entropy, round(list_dot_product(a.z, b.z), 6) AS cos FROM dh JOIN z a ON a.id = dh.id JOIN z b ON b.id = 0"))
def _(spark, d):
    udf.register(spark)
    register_views(spark, d, ["documents", "embeddings"])
    return spark.sql("SELECT d.doc_id AS sample_id, round(sl_entropy(d.text), 6) AS entropy, round(sl_cosine(a.embedding, b.embedding), 6) AS cos FROM documents d JOIN embeddings a ON a.vec_id = d.doc_id JOIN embeddings b ON b.vec_id = 0")


