"""Shared helpers: shared-folder tables, size-checked broadcasts, Arrow text access."""

from __future__ import annotations

import atexit
import ctypes
import shutil
import tempfile
import threading
import uuid
from collections.abc import Callable
from functools import wraps

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

try:
    _trim = ctypes.CDLL(None).malloc_trim
except (AttributeError, OSError, TypeError):  # another C library
    _trim = None

BROADCAST_ROWS = 2_000_000  # narrow rows (a few longs); beyond it joins shuffle
HOT_KEYS = 20_000  # a key is hot when over 1/HOT_KEYS of all rows (and over HOT_ROWS) are its own, so fewer than HOT_KEYS are
HOT_ROWS = 100


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """Folder that the driver and all executors share: spark.checkpoint.dir. In local mode one of our own where that is unset; on a cluster it must be set."""
    conf = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not conf:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        conf = getattr(shared_dir, "own", None)
        if conf is None:
            own = tempfile.mkdtemp(prefix="subsetlab-")
            atexit.register(shutil.rmtree, own, ignore_errors=True)
            conf = shared_dir.own = "file://" + own
    return conf.rstrip("/")


_here = threading.local()


def _made() -> list[str]:
    """Folders that this thread made and nobody deleted yet."""
    if not hasattr(_here, "made"):
        _here.made = []
    return _here.made


def new_path(spark: SparkSession, name: str) -> str:
    _made().append(f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex[:12]}")
    return _made()[-1]


def cleanup(spark: SparkSession, keep: tuple[str, ...] = (), since: int = 0) -> None:
    """Delete the folders that this thread made in the shared folder (from the since-th on), but those in keep; results that still read them are lost."""
    for path in [p for p in _made()[since:] if p not in keep]:
        place = spark._jvm.org.apache.hadoop.fs.Path(path)
        place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)
        _made().remove(path)


def keep_read(spark: SparkSession, since: int, *results: DataFrame, folders: tuple[str, ...] = ()) -> None:
    """Delete the folders made from the since-th on that neither the results read nor folders names."""
    read = {part for r in results for file in r.inputFiles() for part in file.split("/")}
    cleanup(spark, tuple(p for p in _made() if p in folders or p.rsplit("/", 1)[1] in read), since)


def made_so_far() -> int:
    return len(_made())


def tidy(build: Callable[..., DataFrame]) -> Callable[..., DataFrame]:
    """Decorator of a function of (spark, ...): when it returns, the tables that it wrote on the way and its result does not read are deleted."""

    @wraps(build)
    def run(spark: SparkSession, *args, **kwargs) -> DataFrame:
        since = made_so_far()
        out = build(spark, *args, **kwargs)
        keep_read(spark, since, out)
        return out

    return run


def materialize(spark: SparkSession, df: DataFrame, name: str) -> DataFrame:
    """Write df as Parquet into the shared folder and read it back: cuts lineage and survives lost executors."""
    path = new_path(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def small_side(df: DataFrame, limit: int = BROADCAST_ROWS) -> DataFrame:
    """Broadcast df only after counting at most limit rows; else leave the join to shuffle."""
    return F.broadcast(df) if df.count() <= limit else df


def join_group(left: DataFrame, groups: DataFrame, key: str, weight: str, id_: str) -> DataFrame:
    """left LEFT JOIN groups, which has a row for each key and in weight the number of left's rows of that key.

    Hot keys are broadcast: there are fewer than HOT_KEYS of them, whatever the size of the tables. Their rows find their
    group before the exchange and pass it under keys of their own, dealt by id_, so no task gets a hot key's rows.
    Nulls of key stay unmatched and are dealt likewise. groups is read twice and should be a table.
    """
    values = [c for c in groups.columns if c != key]
    total = groups.agg(F.coalesce(F.sum(weight), F.lit(0))).first()[0]
    bound = max(HOT_ROWS, total // HOT_KEYS)
    hot = groups.filter(F.col(weight) > bound).select(F.col(key).alias("_key"), F.struct(*values).alias("_hot"))
    cold = groups.filter(F.col(weight) <= bound).select(F.col(key).cast("string").alias("_key"), F.struct(*values).alias("_cold"))
    found = left.join(F.broadcast(hot), left[key] == hot["_key"], "left").drop("_key")
    alone = F.concat(F.lit("#"), F.xxhash64(id_).cast("string"))  # no group has such a key
    dealt = found.withColumn("_key", F.when(F.col("_hot").isNull() & F.col(key).isNotNull(), F.col(key).cast("string")).otherwise(alone))
    both = dealt.join(cold.hint("merge"), "_key", "left").withColumn("_group", F.coalesce("_hot", "_cold"))
    return both.select(*left.columns, *[F.col("_group")[v].alias(v) for v in values])


def released(batches):
    """The batches; after each one, memory that Arrow and the C library hold unused goes back to the system."""
    for batch in batches:
        yield batch
        del batch
        pa.default_memory_pool().release_unused()
        if _trim is not None:
            _trim(0)


def text_buffer(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes and row offsets of a string column; null counts as empty."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    if col.null_count:
        col = col.fill_null("")
    wide = pa.types.is_large_string(col.type) or pa.types.is_large_binary(col.type)
    bufs, n = col.buffers(), len(col)
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offs = np.frombuffer(bufs[1], np.int64 if wide else np.int32)[col.offset : col.offset + n + 1].astype(np.int64)
    data = np.frombuffer(bufs[2], np.uint8) if bufs[2] is not None and bufs[2].size else np.zeros(0, np.uint8)
    return data[offs[0] : offs[-1]], offs - offs[0]


def doc_blocks(offs: np.ndarray, limit: int = 1 << 19):
    """Ranges of whole rows of about limit bytes each (one row at least), so temporary arrays stay bounded."""
    i, n = 0, len(offs) - 1
    while i < n:
        j = int(np.searchsorted(offs, offs[i] + limit, "right")) - 1
        j = min(n, max(j, i + 1))
        yield i, j
        i = j
