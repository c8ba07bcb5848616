"""WARC archives: writer, normaliser of whole-file gzip, sidecar offset index, reader.

Many crawls gzip an archive as one stream, which can only be read from its start. The normaliser inflates such a stream
once, in bounded memory, writes every record as a gzip member of its own and notes its offset; afterwards any record
can be read by seeking, so reading splits within files. Files live in the shared folder and are reached through
pyarrow's filesystems; a task names its files anew at every attempt, and only files that a finished task reports count.
"""

from __future__ import annotations

import base64
import hashlib
import json
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import join_group, keep_read, made_so_far, materialize, new_path, released, table

PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = "2024-01-01T00:00:00Z"
FILE_BYTES = 64 << 20  # uncompressed bytes of an archive before the next one begins
SPLIT_BYTES = 1 << 20  # compressed bytes that are read in one go
TASK_BYTES = 8 << 20  # compressed bytes of a reading task
ANSWER_ROWS = 200_000  # shared payloads whose digests and pages are broadcast at most
CHUNK = 1 << 18


def payload_digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record_head(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None) -> bytes:
    """WARC header and HTTP head of a page; a revisit's block ends there."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    lines = ["WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: <urn:page:{'' if page_id is None else page_id}>", f"WARC-Date: {DATE}"]
    if url:
        lines.append("WARC-Target-URI: " + "".join(c for c in url if c >= " "))
    lines.append(f"WARC-Payload-Digest: sha1:{payload_digest(payload)}")
    if refers_to is not None:
        lines += [f"WARC-Profile: {PROFILE}", f"WARC-Refers-To: <urn:page:{refers_to}>"]
    lines += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(http) + (len(payload) if refers_to is None else 0)}"]
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + http


def parse_head(head: bytes) -> dict[str, str]:
    """Header fields in lower case; the version line under ''."""
    first, *lines = head.decode("utf-8", "replace").split("\r\n")
    out = {"": first}
    for line in lines:
        name, _, value = line.partition(":")
        out[name.strip().lower()] = value.strip()
    return out


def _page_of(urn: str) -> int | None:
    text = urn.removeprefix("<urn:page:").removesuffix(">")
    return int(text) if text else None


def decide(pages: DataFrame, at_least: int = 0) -> DataFrame:
    """digest, answer, n: payloads of at least at_least bytes that stand in several pages, with the largest page_id and the number of pages."""
    payload = F.coalesce("html", F.lit(""))
    rows = pages.filter(F.octet_length(payload) >= at_least).select("page_id", F.sha2(payload, 256).alias("digest"))
    return rows.groupBy("digest").agg(F.max("page_id").alias("answer"), F.count(F.lit(1)).alias("n")).filter("n > 1")


def write_archives(spark: SparkSession, pages: DataFrame, folder: str, at_least: int = 0, level: int = 6) -> DataFrame:
    """Write pages (page_id, url, html) as archives of one gzip stream each; returns (path, records) of the files."""
    answers = materialize(spark, decide(pages, at_least), "answers")
    payload = F.coalesce("html", F.lit(""))
    rows = pages.select("page_id", "url", payload.alias("html"), F.when(F.octet_length(payload) >= at_least, F.sha2(payload, 256)).alias("digest"))
    if answers.count() <= ANSWER_ROWS:
        rows = rows.join(F.broadcast(answers), "digest", "left")
    else:
        rows = join_group(rows, answers, "digest", "n", "page_id")
    revisit = F.when(~F.col("page_id").eqNullSafe(F.col("answer")), F.col("answer"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, root = fs.FileSystem.from_uri(folder)
        out, path, size, records, done = None, "", 0, 0, []

        def close():
            nonlocal out
            if out is not None:
                out.write(packer.flush())
                out.close()
                done.append((path, records))
                out = None

        for batch in released(batches):
            for page, url, html, answer in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                raw = html.encode()
                if out is None:
                    path, size, records = f"{root}/whole-{uuid.uuid4().hex}.warc.gz", 0, 0
                    out, packer = store.open_output_stream(path, compression=None), zlib.compressobj(level, zlib.DEFLATED, 31)
                block = record_head(page, url, raw, answer) + (raw if answer is None else b"") + b"\r\n\r\n"
                out.write(packer.compress(block))
                size, records = size + len(block), records + 1
                if size >= FILE_BYTES:
                    close()
        close()
        yield pa.RecordBatch.from_arrays([pa.array([d[0] for d in done], pa.string()), pa.array([d[1] for d in done], pa.int64())], ["path", "records"])

    return materialize(spark, rows.select("page_id", "url", "html", revisit.alias("answer")).mapInArrow(run, "path string, records long"), "whole-files")


class _Inflater:
    """Bytes of a gzip stream of one or more members, read forward in bounded memory."""

    def __init__(self, source):
        self.source, self.unpack, self.ready, self.rest = source, zlib.decompressobj(31), bytearray(), b""

    def fill(self) -> bool:
        while True:
            raw = self.rest or self.source.read(CHUNK)
            if not raw:
                return False
            out = self.unpack.decompress(raw, CHUNK)
            self.rest = self.unpack.unconsumed_tail
            if self.unpack.eof:
                self.rest, self.unpack = self.unpack.unused_data, zlib.decompressobj(31)
            if out:
                self.ready += out
                return True

    def head(self) -> bytes | None:
        """Up to and with the empty line of the next record's header; None at the end."""
        while (at := self.ready.find(b"\r\n\r\n")) < 0:
            if not self.fill():
                if self.ready.strip():
                    raise ValueError("archive ends inside a header")
                return None
        return self.take(at + 4)

    def take(self, n: int) -> bytes:
        while len(self.ready) < n:
            if not self.fill():
                raise ValueError("archive ends inside a record")
        out = bytes(self.ready[:n])
        del self.ready[:n]
        return out

    def parts(self, n: int) -> Iterator[bytes]:
        while n:
            if not self.ready and not self.fill():
                raise ValueError("archive ends inside a record")
            out = self.take(min(n, len(self.ready)))
            n -= len(out)
            yield out


def normalise_stream(source, sink, level: int = 6) -> Iterator[dict]:
    """Rewrite every record of source as a member of its own in sink; yields the index entries."""
    stream, at = _Inflater(source), 0
    while (head := stream.head()) is not None:
        fields = parse_head(head[:-4])
        packer, begin = zlib.compressobj(level, zlib.DEFLATED, 31), at
        length = int(fields["content-length"])

        def put(raw: bytes) -> None:
            nonlocal at
            at += sink.write(raw)

        put(packer.compress(head))
        for part in stream.parts(length):
            put(packer.compress(part))
        if stream.take(4) != b"\r\n\r\n":
            raise ValueError(f"no end after the record at {begin}")
        put(packer.compress(b"\r\n\r\n") + packer.flush())
        yield {"offset": begin, "length": at - begin, "record_id": fields.get("warc-record-id", ""), "type": fields.get("warc-type", "")}


def normalise(spark: SparkSession, files: DataFrame, folder: str, level: int = 6) -> DataFrame:
    """archive, offset, length, record_id, type of every record; the same entries lie beside each archive as JSON lines (.idx)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, root = fs.FileSystem.from_uri(folder)
        for batch in released(batches):
            for path in batch.column(0).to_pylist():
                name = f"{root}/records-{uuid.uuid4().hex}.warc.gz"
                entries = []
                with store.open_input_stream(path, compression=None) as source, store.open_output_stream(name, compression=None) as sink, store.open_output_stream(name + ".idx", compression=None) as side:
                    for e in normalise_stream(source, sink, level):
                        side.write((json.dumps(e) + "\n").encode())
                        entries.append(e)
                        if len(entries) == 10_000:
                            yield _entries(name, entries)
                            entries = []
                yield _entries(name, entries)

    return materialize(spark, files.select("path").mapInArrow(run, "archive string, offset long, length long, record_id string, type string"), "archive-index")


def _entries(name: str, entries: list[dict]) -> pa.RecordBatch:
    cols = [pa.array([name] * len(entries), pa.string())] + [pa.array([e[k] for e in entries], t) for k, t in (("offset", pa.int64()), ("length", pa.int64()), ("record_id", pa.string()), ("type", pa.string()))]
    return pa.RecordBatch.from_arrays(cols, ["archive", "offset", "length", "record_id", "type"])


def read_records(index: DataFrame, folder: str, payloads: bool = False) -> DataFrame:
    """page_id, url, payload_bytes, payload_digest, record_type, refers_to (and payload, null for revisits) by seeking.

    A response's digest and length are computed from its payload and compared with its header; a mismatch raises.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, _ = fs.FileSystem.from_uri(folder)
        name, source = None, None
        for batch in released(batches):
            rows = []
            for archive, offset, length in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True):
                if archive != name:
                    if source:
                        source.close()
                    name, source = archive, store.open_input_file(archive)
                source.seek(offset)
                head, _, rest = zlib.decompress(source.read(length), 31).partition(b"\r\n\r\n")
                f = parse_head(head)
                block = rest[: int(f["content-length"])]
                http, _, body = block.partition(b"\r\n\r\n")
                n, digest = int(parse_head(http)["content-length"]), f["warc-payload-digest"].removeprefix("sha1:")
                revisit = f["warc-type"] == "revisit"
                if not revisit and (len(body) != n or payload_digest(body) != digest):
                    raise ValueError(f"payload of {f['warc-record-id']} does not match its header")
                rows.append((_page_of(f["warc-record-id"]), f.get("warc-target-uri"), n, digest, f["warc-type"], _page_of(f["warc-refers-to"]) if revisit else None, None if revisit or not payloads else body))
            cols = list(zip(*rows, strict=True)) or [()] * 7
            kinds = [pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.binary()]
            names = ["page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to", "payload"]
            keep = 7 if payloads else 6
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols[:keep], kinds[:keep], strict=True)], names[:keep])
        if source:
            source.close()

    # The number of tasks follows from the bytes to read: by the index's own few bytes Spark would merge them into one.
    size = index.agg(F.coalesce(F.sum("length"), F.lit(0))).first()[0]
    tasks = max(index.sparkSession.sparkContext.defaultParallelism, -(-size // TASK_BYTES))
    group = F.floor(F.col("offset") / SPLIT_BYTES)
    rows = index.select("archive", "offset", "length").repartition(tasks, "archive", group).sortWithinPartitions("archive", "offset")
    return rows.mapInArrow(run, "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long" + ", payload binary" * payloads)


def archive_round_trip(spark: SparkSession, pages: DataFrame, folder: str | None = None, at_least: int = 0, payloads: bool = False) -> DataFrame:
    """Write pages as whole-file gzip, normalise the files, read every record back; one row per page row.

    Null html is an empty payload. Of equal payloads of at least at_least bytes the largest page_id is the response and
    the others revisit it; rows that repeat that page_id with that payload are responses too. A null page_id is written
    without number and revisits if it can. Null urls are left out of the header. An empty table gives no rows. The
    normalised archives and their indexes stay in folder; the whole-file ones are deleted.
    """
    since = made_so_far()
    folder, whole = folder or new_path(spark, "warc"), new_path(spark, "warc-whole")
    _make(folder)
    _make(whole)
    pages = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html")
    files = write_archives(spark, pages, whole, at_least)
    index = normalise(spark, files.repartition(max(1, files.count())), folder)
    out = read_records(index, folder, payloads)
    keep_read(spark, since, out, folders=(folder,))
    return out


def _make(folder: str) -> None:
    store, root = fs.FileSystem.from_uri(folder)
    store.create_dir(root, recursive=True)


def op2_warc_normaliser(spark: SparkSession, sf_dir: str) -> DataFrame:
    return archive_round_trip(spark, table(spark, sf_dir, "pages")).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")
