"""Readers, writers and sinks."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import threading
import uuid
from collections.abc import Callable, Iterator
from functools import wraps

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ..functions.levels import LUMA, equal_weights
from ..schemas import SampleSpec


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load_samples(spark: SparkSession, sf_dir: str, spec: SampleSpec) -> DataFrame:
    return spec.bind(table(spark, sf_dir, spec.table))


def register_views(spark: SparkSession, sf_dir: str, names: list[str]) -> None:
    for name in names:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def read(spark: SparkSession, path: str, fmt: str, schema: StructType | str | None = None, **options) -> DataFrame:
    """parquet, csv, json, orc, text or binaryFile. CSV and JSON need a schema (no second pass over the data)."""
    if fmt in ("csv", "json") and schema is None:
        raise ValueError(f"{fmt} needs a schema")
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def read_files(spark: SparkSession, path: str, pattern: str = "*") -> DataFrame:
    """(sample_id, payload, stratum): raw files as byte payloads; the id is a hash of the path.

    For uncompressed files. The bytes of a compressed image say nothing about its grey levels: read_images decodes them.
    """
    files = spark.read.format("binaryFile").option("pathGlobFilter", pattern).option("recursiveFileLookup", "true").load(path)
    return files.select(F.xxhash64("path").alias("sample_id"), F.col("content").alias("payload"), F.lit(None).cast("string").alias("stratum"))


def read_images(spark: SparkSession, path: str, pattern: str = "*", weights: dict[int, tuple[float, ...]] | None = None) -> DataFrame:
    """(sample_id, payload, stratum, height, width, bands): decoded images, the payload one byte of grey level for each pixel.

    PNG, JPEG, GIF and BMP files of one, three or four bands; what cannot be decoded is left out. Grey is the weighted sum
    of the bands in file order (red, green, blue, and the fourth), rounded: luminance weights for three bands, equal ones
    for four, unless weights has others by number of bands. The id is a hash of the path.
    """
    weights = {1: (1.0,), 3: LUMA, 4: equal_weights(4)} | (weights or {})
    files = spark.read.format("image").option("dropInvalid", True).option("pathGlobFilter", pattern).option("recursiveFileLookup", "true").load(path)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            gray = []
            for n, data in zip(batch.column(3).to_pylist(), batch.column(4), strict=True):
                pixels = np.frombuffer(data.as_buffer(), np.uint8).reshape(-1, n)
                order = [0] if n == 1 else [2, 1, 0, 3][:n]  # decoded pixels begin with blue
                gray.append(np.clip(np.rint(pixels[:, order] @ np.array(weights[n])), 0, 255).astype(np.uint8).tobytes())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(gray, pa.binary()), *batch.columns[1:4]], ["sample_id", "payload", "height", "width", "bands"])

    rows = files.select(F.xxhash64("image.origin").alias("sample_id"), "image.height", "image.width", "image.nChannels", "image.data")
    out = rows.mapInArrow(run, "sample_id long, payload binary, height int, width int, bands int")
    return out.select("sample_id", "payload", F.lit(None).cast("string").alias("stratum"), "height", "width", "bands")


def stream(spark: SparkSession, path: str, fmt: str, schema: StructType, **options) -> DataFrame:
    return spark.readStream.format(fmt).schema(schema).options(**options).load(path)


def write(df: DataFrame, path: str, fmt: str = "parquet", partition_by: tuple[str, ...] = (), mode: str = "errorifexists") -> None:
    writer = df.write.format(fmt).mode(mode)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def write_bucketed(df: DataFrame, name: str, buckets: int, column: str, mode: str = "overwrite") -> None:
    """Bucketed and sorted table: later joins on the column need no exchange."""
    df.write.mode(mode).bucketBy(buckets, column).sortBy(column).saveAsTable(name)


def write_manifest(selected: DataFrame, path: str) -> None:
    """Ids only, sorted within files."""
    selected.select("sample_id").sortWithinPartitions("sample_id").write.mode("overwrite").parquet(path)


def materialize_selection(samples: DataFrame, selected: DataFrame) -> DataFrame:
    """The unchanged samples that were selected: a semi join on ids, so payloads are read once more and not enlarged."""
    return samples.join(selected.select("sample_id"), "sample_id", "left_semi")


def work_dir(spark: SparkSession) -> str:
    """Folder that the driver and all executors share: spark.checkpoint.dir. In local mode one of our own where it is unset; on a cluster it must be set."""
    conf = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not conf:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        conf = getattr(work_dir, "own", None)
        if conf is None:
            own = tempfile.mkdtemp(prefix="subsetlab-")
            atexit.register(shutil.rmtree, own, ignore_errors=True)
            conf = work_dir.own = "file://" + own
    return conf.rstrip("/")


_here = threading.local()


def stage(spark: SparkSession, df: DataFrame, name: str) -> DataFrame:
    """Write a narrow stage table into the shared folder and read it back: later steps reuse it, lost executors cost little."""
    path = f"{work_dir(spark)}/{name}-{uuid.uuid4().hex[:12]}"
    df.write.parquet(path)
    staged().append(path)
    return spark.read.schema(df.schema).parquet(path)


def staged() -> list[str]:
    """Stage folders of this thread that are still there."""
    if not hasattr(_here, "paths"):
        _here.paths = []
    return _here.paths


def drop_stages(spark: SparkSession, since: int = 0, *results: DataFrame) -> None:
    """Delete this thread's stage folders, from the since-th on, that the results do not read."""
    read = {part for r in results for file in r.inputFiles() for part in file.split("/")}
    for path in [p for p in staged()[since:] if p.rsplit("/", 1)[1] not in read]:
        place = spark._jvm.org.apache.hadoop.fs.Path(path)
        place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)
        staged().remove(path)


def tidy(build: Callable[..., DataFrame]) -> Callable[..., DataFrame]:
    """Decorator of a function of (spark, ...): when it returns, the stage tables that its result does not read are deleted."""

    @wraps(build)
    def run(spark: SparkSession, *args, **kwargs) -> DataFrame:
        since = len(staged())
        out = build(spark, *args, **kwargs)
        drop_stages(spark, since, out)
        return out

    return run
