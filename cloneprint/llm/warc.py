"""WARC as a Spark data source: ``spark.read.format("warc")`` and ``df.write.format("warc")``.

Writing: a gzip member per record, whose extra field tells the member's length, and beside each archive an index with the offset of every
``STRIDE``-th record. Tasks write under names of their own; the commit moves the files into place, so retried or lost tasks leave nothing.

Reading: partitions are byte ranges of archives, cut at indexed records and gathered up to ``split`` bytes. Predicates on record type and
headers (options, or filters that Spark pushes down) are tested on a record's headers, of which only the first bytes are inflated; a
record that fails them, and every payload if ``payload`` is false, is skipped without being decoded. Plain ``.warc`` files are read too.

Defined cases: a null or empty payload is a record with an empty payload; unknown headers stay in ``headers``; a folder without archives gives no rows;
a damaged digest raises. Equal rows are written as often as they occur.
"""

from __future__ import annotations

import base64
import hashlib
import io
import struct
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceArrowWriter, DataSourceReader, EqualTo, Filter, In, InputPartition, StringStartsWith, WriterCommitMessage

from .common import Scratch

STRIDE, SPLIT, HEAD = 64, 64 << 20, 2048
SCHEMA = "record_id string, record_type string, target_uri string, refers_to string, payload_bytes long, payload_digest string, headers map<string,string>, payload binary"
ROW = "record_id string, record_type string, target_uri string, refers_to string, payload binary"
#: columns that stand for one header each
HEADER = {"record_id": "WARC-Record-ID", "record_type": "WARC-Type", "target_uri": "WARC-Target-URI", "refers_to": "WARC-Refers-To", "payload_digest": "WARC-Payload-Digest"}
DATE = "2020-01-01T00:00:00Z"


def digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record(kind: str, record_id: str, uri: str | None, refers_to: str | None, payload: bytes) -> bytes:
    """One record; a revisit keeps the HTTP header, which tells the payload's length, and leaves the payload out."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http if kind == "revisit" else http + payload
    clean = " ".join((uri or "").split())
    lines = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: {record_id}", f"WARC-Date: {DATE}", f"WARC-Payload-Digest: sha1:{digest(payload)}", "Content-Type: application/http; msgtype=response"]
    if uri is not None:
        lines.append(f"WARC-Target-URI: {clean}")
    if kind == "revisit":
        lines += [f"WARC-Refers-To: {refers_to}", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    return ("\r\n".join([*lines, f"Content-Length: {len(block)}"]) + "\r\n\r\n").encode() + block + b"\r\n\r\n"


def member(data: bytes) -> bytes:
    """A gzip member whose extra field ``sl`` holds its length and the inflated length."""
    deflate = zlib.compressobj(1, zlib.DEFLATED, -15)
    body = deflate.compress(data) + deflate.flush()
    size = 12 + 12 + len(body) + 8
    head = struct.pack("<4BI2BH2sHII", 31, 139, 8, 4, 0, 0, 255, 12, b"sl", 8, size & 0xFFFFFFFF, len(data) & 0xFFFFFFFF)
    return head + body + struct.pack("<II", zlib.crc32(data), len(data) & 0xFFFFFFFF)


def _headers(raw: bytes) -> dict[str, str]:
    out = {}
    for line in raw.split(b"\r\n")[1:]:
        name, colon, value = line.partition(b":")
        if colon:
            out[name.decode("utf-8", "replace").strip()] = value.decode("utf-8", "replace").strip()
    return out


def _inflated(file, at: int) -> tuple[bytes, int]:
    """A whole gzip member and its length, found by inflating it."""
    inflate, parts, pos = zlib.decompressobj(31), [], at
    while not inflate.eof:
        got = file.read_at(1 << 16, pos)
        if not got:
            break
        parts.append(inflate.decompress(got))
        pos += len(got)
    return b"".join(parts), pos - at - len(inflate.unused_data)


@dataclass
class Wanted:
    """What a record's headers must hold; None takes any value."""

    equal: list[tuple[str, set[str]]]
    prefix: list[tuple[str, str]]

    def fits(self, headers: dict[str, str]) -> bool:
        low = {k.lower(): v for k, v in headers.items()}
        value = lambda name: _plain(name, low.get(name.lower()))
        return all(value(n) in v for n, v in self.equal) and all((value(n) or "").startswith(p) for n, p in self.prefix)


def _plain(name: str, value: str | None) -> str | None:
    return value.removeprefix("sha1:") if value and name == HEADER["payload_digest"] else value


def records(file, start: int, end: int, zipped: bool, wanted: Wanted, payload: bool) -> Iterator[tuple[dict[str, str], bytes, bytes | None]]:
    """(headers, first bytes of the block, block or None) of the records that begin in start..end and are wanted."""
    at = start
    while at < end:
        size, data = None, None
        if zipped:
            head = file.read_at(min(24, end - at), at)
            if len(head) >= 24 and head[3] & 4 and head[12:14] == b"sl":
                size = struct.unpack_from("<I", head, 16)[0]
                first = zlib.decompressobj(31).decompress(file.read_at(min(HEAD, size), at), 2 * HEAD)
            if size is None or b"\r\n\r\n" not in first:  # of unknown length, or with unusually long headers
                data, size = _inflated(file, at)
                first = data
        else:
            first = file.read_at(2 * HEAD, at)
            while b"\r\n\r\n" not in first and at + len(first) < end:
                first = file.read_at(2 * len(first), at)
        raw, _, rest = first.partition(b"\r\n\r\n")
        headers = _headers(raw)
        length = int(headers.get("Content-Length", "0"))
        total, fits, block = len(raw) + 4 + length + 4, wanted.fits(headers), None
        if fits and payload:
            if zipped:
                data = data if data is not None else zlib.decompress(file.read_at(size, at), 31)
                block = data[len(raw) + 4 : len(raw) + 4 + length]
            else:
                block = file.read_at(length, at + len(raw) + 4)
        if fits:
            yield headers, rest[:length], block if payload else None
        at += size if zipped else total


@dataclass
class Range(InputPartition):
    parts: list[tuple[str, int, int]]


def _listing(folder: str) -> tuple[pafs.FileSystem, list[pafs.FileInfo]]:
    store, path = pafs.FileSystem.from_uri(folder) if ":" in folder.split("/", 1)[0] else (pafs.LocalFileSystem(), folder)
    found = store.get_file_info(pafs.FileSelector(path, recursive=True, allow_not_found=True))
    return store, sorted((f for f in found if f.is_file), key=lambda f: f.path)


class WarcReader(DataSourceReader):
    def __init__(self, options: dict[str, str]):
        self.folder, self.split = options["path"], int(options.get("split", SPLIT))
        self.payload = options.get("payload", "true").lower() == "true"
        self.wanted = Wanted([], [])
        if types := options.get("record_types", options.get("recordtypes")):
            self.wanted.equal.append((HEADER["record_type"], {t.strip() for t in types.split(",")}))
        for name, value in options.items():
            if name.lower().startswith("header."):
                self.wanted.equal.append((name[7:], {value}))

    def pushFilters(self, filters: list[Filter]):
        for f in filters:
            name = HEADER.get(f.attribute[0]) if len(getattr(f, "attribute", ())) == 1 else None
            if name and isinstance(f, EqualTo) and isinstance(f.value, str):
                self.wanted.equal.append((name, {f.value}))
            elif name and isinstance(f, In) and all(isinstance(v, str) for v in f.value):
                self.wanted.equal.append((name, set(f.value)))
            elif name and isinstance(f, StringStartsWith):
                self.wanted.prefix.append((name, f.value))
            else:
                yield f

    def partitions(self):
        store, files = _listing(self.folder)
        index = {f.path for f in files if f.path.endswith(".idx")}
        out, held, size = [], [], 0
        for f in files:
            if not f.path.endswith((".warc", ".warc.gz")):
                continue
            cuts = [0]
            if f.path + ".idx" in index and f.size > self.split:
                with store.open_input_file(f.path + ".idx") as x:
                    for at in memoryview(x.read()).cast("q"):
                        if at - cuts[-1] >= self.split:
                            cuts.append(at)
            for a, b in zip(cuts, [*cuts[1:], f.size], strict=True):
                held.append((f.path, a, b))
                size += b - a
                if size >= self.split:
                    out.append(Range(held))
                    held, size = [], 0
        return [*out, Range(held)] if held or not out else out

    def read(self, partition: Range):
        store, _ = pafs.FileSystem.from_uri(self.folder) if ":" in self.folder.split("/", 1)[0] else (pafs.LocalFileSystem(), "")
        names = [c.split()[0] for c in SCHEMA.split(", ")]
        kinds = [pa.string()] * 4 + [pa.int64(), pa.string(), pa.map_(pa.string(), pa.string()), pa.binary()]
        rows, size = [], 0

        def batch():
            return pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate(kinds)], names)

        for path, start, end in partition.parts:
            with store.open_input_file(path) as file:
                for headers, first, block in records(file, start, end, path.endswith(".gz"), self.wanted, self.payload):
                    low = {k.lower(): v for k, v in headers.items()}
                    kind, told = low.get("warc-type"), _plain(HEADER["payload_digest"], low.get("warc-payload-digest"))
                    http = "http" in low.get("content-type", "")
                    head, _, body = (block if block is not None else first).partition(b"\r\n\r\n") if http else (b"", b"", block)
                    told_length = _headers(head).get("Content-Length") if http else low.get("content-length")
                    value = None if block is None or kind == "revisit" else body
                    if value is not None and told and digest(value) != told:
                        raise ValueError(f"{path}: the payload of {low.get('warc-record-id')} does not have its digest")
                    length = len(value) if value is not None else int(told_length or 0)
                    rows.append((low.get("warc-record-id"), kind, low.get("warc-target-uri"), low.get("warc-refers-to"), length, told, list(headers.items()), value))
                    size += 500 + len(value or b"")
                    if size > 8 << 20:
                        yield batch()
                        rows, size = [], 0
        yield batch()


@dataclass
class Written(WriterCommitMessage):
    temps: list[str]


class WarcWriter(DataSourceArrowWriter):
    def __init__(self, options: dict[str, str], overwrite: bool):
        self.folder, self.overwrite = options["path"], overwrite

    def _store(self):
        return pafs.FileSystem.from_uri(self.folder) if ":" in self.folder.split("/", 1)[0] else (pafs.LocalFileSystem(), self.folder)

    def write(self, iterator: Iterator[pa.RecordBatch]) -> WriterCommitMessage:
        store, path = self._store()
        base, out, at, n, index = f"{path}/_tmp-{uuid.uuid4().hex}", None, 0, 0, io.BytesIO()
        for b in iterator:
            for row in zip(*(b.column(c).to_pylist() for c in ("record_type", "record_id", "target_uri", "refers_to", "payload")), strict=True):
                if out is None:
                    store.create_dir(path, recursive=True)
                    out = store.open_output_stream(f"{base}.warc.gz.part")
                if n % STRIDE == 0:
                    index.write(struct.pack("<q", at))
                data = member(record(*row[:4], row[4] or b""))
                out.write(data)
                at, n = at + len(data), n + 1
        if out is None:
            return Written([])
        out.close()
        with store.open_output_stream(f"{base}.idx.part") as x:
            x.write(index.getvalue())
        return Written([base])

    def commit(self, messages):
        store, path = self._store()
        store.create_dir(path, recursive=True)
        if self.overwrite:
            for f in store.get_file_info(pafs.FileSelector(path)):
                if f.is_file and f.base_name.startswith("part-"):
                    store.delete_file(f.path)
        job = uuid.uuid4().hex[:8]
        for k, base in enumerate(t for m in messages if m for t in m.temps):
            store.move(f"{base}.idx.part", f"{path}/part-{k:06d}-{job}.warc.gz.idx")
            store.move(f"{base}.warc.gz.part", f"{path}/part-{k:06d}-{job}.warc.gz")

    def abort(self, messages):
        store, _ = self._store()
        for base in (t for m in messages if m for t in m.temps):
            for f in (f"{base}.idx.part", f"{base}.warc.gz.part"):
                if store.get_file_info(f).is_file:
                    store.delete_file(f)


class WarcSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "warc"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema):
        return WarcReader(dict(self.options))

    def writer(self, schema, overwrite: bool):
        return WarcWriter(dict(self.options), overwrite)


def register(spark: SparkSession) -> None:
    """Makes the format known; the setting (a runtime one) lets Spark push filters to Python sources."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(WarcSource)


def page_records(pages: DataFrame, scratch: Scratch, least: int = 0) -> DataFrame:
    """A record row per page; of pages with equal payloads of at least ``least`` bytes, all but the smallest page_id revisit it."""
    payload = F.coalesce(F.encode(F.col("html").cast("string"), "UTF-8"), F.lit(b""))
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("target_uri"), payload.alias("payload"))
    rows = rows.withColumn("same", F.sha2("payload", 256)).withColumn("size", F.octet_length("payload"))
    # copies are found among narrow rows; payloads then meet their answer by page, a key that no group of copies makes hot
    narrow = scratch.keep(rows.where(F.col("size") >= least).select("page_id", "same"), "digests")
    first = narrow.groupBy("same").agg(F.min("page_id").alias("first"), F.count("*").alias("n")).where("n > 1 and first is not null").select("same", "first")
    again = scratch.keep(narrow.join(first, "same").where("page_id is null or page_id <> first").select(F.col("page_id").alias("page"), F.col("same").alias("digest"), "first").distinct(), "again")
    name = lambda c: F.concat(F.lit("<urn:page:"), F.coalesce(F.col(c).cast("string"), F.lit("none")), F.lit(">"))
    met = rows.join(again, rows["page_id"].eqNullSafe(again["page"]) & (rows["same"] == again["digest"]), "left")
    found = F.col("first").isNotNull()
    return met.select(name("page_id").alias("record_id"), F.when(found, "revisit").otherwise("response").alias("record_type"), "target_uri", F.when(found, name("first")).alias("refers_to"), "payload")


def round_trip(pages: DataFrame, least: int = 0) -> DataFrame:
    """Writes the pages as archives and reads them back: page_id, payload_bytes, payload_digest, record_type, refers_to."""
    spark, scratch = pages.sparkSession, Scratch(pages.sparkSession, "warc")
    register(spark)
    page_records(pages, scratch, least).write.format("warc").mode("append").option("path", scratch.path("archives")).save()
    read = spark.read.format("warc").option("path", scratch.path("archives")).load()
    page = lambda c: F.regexp_extract(c, "<urn:page:(-?[0-9]+)>", 1)
    return read.select(
        F.when(page("record_id") != "", page("record_id").cast("long")).alias("page_id"), "payload_bytes", "payload_digest", "record_type", F.when(page("refers_to") != "", page("refers_to").cast("long")).alias("refers_to")
    )
