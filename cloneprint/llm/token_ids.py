"""Binary token ids: fixed-width bit packing with block offsets.

A file holds blocks of ``BLOCK`` ids (the last may be shorter), each id in the fewest bits that hold the
vocabulary's largest, each block on a byte boundary; then a footer: doc_ids, the documents' first ids, block
offsets, all as little-endian 64-bit integers; then a trailer: bits, ids, documents, blocks, footer offset, mark. Files of a
folder follow ascending doc_id. Any run of ids is read by seeking to its blocks and unpacking them in numpy.

Defined cases: a null or empty text has the end id alone; rows with equal doc_id are kept in one file, in the order of their texts'
hash; a null doc_id sorts first and is stored as such; an empty table gives one empty file or none, and no rows. Other columns are ignored.
"""

from __future__ import annotations

import struct
import uuid
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch
from .encode import encoder

BLOCK, MARK, NO_ID = 8192, b"PKID0001", -(1 << 63)
TRAILER = struct.Struct("<qqqqq8s")


def width(vocabulary: int) -> int:
    """Bits that hold ids 0..vocabulary-1."""
    return max(1, (max(1, vocabulary) - 1).bit_length())


def pack_bits(ids: np.ndarray, bits: int) -> bytes:
    ids = np.asarray(ids, "<u4")
    if bits == 16:
        return ids.astype("<u2").tobytes()
    rows = np.unpackbits(ids.view(np.uint8).reshape(-1, 4), axis=1, bitorder="little")[:, :bits]
    return np.packbits(rows.reshape(-1), bitorder="little").tobytes()


def unpack_bits(data: bytes, bits: int, n: int) -> np.ndarray:
    if bits == 16:
        return np.frombuffer(data, "<u2", n).astype("<u4")
    rows = np.zeros((n, 32), np.uint8)
    rows[:, :bits] = np.unpackbits(np.frombuffer(data, np.uint8), count=n * bits, bitorder="little").reshape(n, bits)
    return np.packbits(rows, axis=1, bitorder="little").reshape(-1).view("<u4")


def open_store(uri: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(uri) if "://" in uri or uri.startswith("file:") else (pafs.LocalFileSystem(), uri)


class Writer:
    """Streams ids into one file; memory holds a block and the document index."""

    def __init__(self, uri: str, bits: int):
        self.store, self.path = open_store(uri)
        self.store.create_dir(self.path.rsplit("/", 1)[0], recursive=True)
        self.temp = f"{self.path}.{uuid.uuid4().hex}.tmp"
        self.out, self.bits = self.store.open_output_stream(self.temp), bits
        self.waiting: list[np.ndarray] = []
        self.held = self.total = self.at = 0
        self.docs: list[int] = []
        self.starts: list[int] = []
        self.blocks: list[int] = []

    def add(self, doc_id: int | None, ids: np.ndarray) -> None:
        self.docs.append(NO_ID if doc_id is None else doc_id)
        self.starts.append(self.total)
        self.total += len(ids)
        self.waiting.append(ids)
        self.held += len(ids)
        if self.held >= 64 * BLOCK:
            self._flush(False)

    def _flush(self, last: bool) -> None:
        ids = np.concatenate(self.waiting) if self.waiting else np.zeros(0, "<u4")
        upto = len(ids) if last else len(ids) // BLOCK * BLOCK
        for k in range(0, upto, BLOCK):
            data = pack_bits(ids[k : min(k + BLOCK, upto)], self.bits)
            self.blocks.append(self.at)
            self.out.write(data)
            self.at += len(data)
        self.waiting, self.held = [ids[upto:]], len(ids) - upto

    def close(self) -> None:
        """The file appears under its name at once and whole, however often a task is tried."""
        self._flush(True)
        for part in (self.docs, self.starts, self.blocks):
            self.out.write(np.array(part, "<i8").tobytes())
        self.out.write(TRAILER.pack(self.bits, self.total, len(self.docs), len(self.blocks), self.at, MARK))
        self.out.close()
        self.store.move(self.temp, self.path)


class Reader:
    """Random access to a file's ids and documents."""

    def __init__(self, uri: str):
        store, path = open_store(uri)
        self.file = store.open_input_file(path)
        size = self.file.size()
        self.bits, self.total, docs, blocks, self.foot, mark = TRAILER.unpack(self.file.read_at(TRAILER.size, size - TRAILER.size))
        if mark != MARK:
            raise ValueError(f"{uri} is no packed id file")
        index = np.frombuffer(self.file.read_at(8 * (2 * docs + blocks), self.foot), "<i8")
        self.docs, self.starts, self.blocks = index[:docs], index[docs : 2 * docs], index[2 * docs :]

    def ids(self, start: int, n: int) -> np.ndarray:
        if n <= 0:
            return np.zeros(0, "<u4")
        first, last = start // BLOCK, (start + n - 1) // BLOCK
        end = int(self.blocks[last + 1]) if last + 1 < len(self.blocks) else self.foot
        data = self.file.read_at(end - int(self.blocks[first]), int(self.blocks[first]))
        held = min((last + 1) * BLOCK, self.total) - first * BLOCK  # whole blocks have no padding bits between them
        return unpack_bits(data, self.bits, held)[start - first * BLOCK : start - first * BLOCK + n]

    def document(self, k: int) -> tuple[int | None, np.ndarray]:
        end = int(self.starts[k + 1]) if k + 1 < len(self.starts) else self.total
        doc = int(self.docs[k])
        return (None if doc == NO_ID else doc), self.ids(int(self.starts[k]), end - int(self.starts[k]))

    def close(self) -> None:
        self.file.close()


def _write(tokenizer: str, end: int, folder: str):
    def run(batches):
        from pyspark import TaskContext

        part, enc, out = TaskContext.get().partitionId(), encoder(tokenizer), None
        tail = np.array([end], "<u4").tobytes()
        for batch in batches:
            docs = batch.column(0).to_pylist()
            for at in range(0, len(docs), 256):
                got = enc.ids([t or "" for t in batch.column(1)[at : at + 256].to_pylist()])
                for doc, ids in zip(docs[at : at + 256], got, strict=True):
                    out = out or Writer(f"{folder}/part-{part:06d}.ids", width(max(enc.size, end + 1)))
                    out.add(doc, np.frombuffer(ids + tail, "<u4"))
        if out:
            out.close()
            yield pa.RecordBatch.from_pydict({"part": pa.array([part], pa.int64()), "n": pa.array([out.total], pa.int64())})

    return run


def write(docs: DataFrame, tokenizer: str, folder: str, end: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Writes the files; gives (part, n): each file's number and ids. Run it once: keep its rows."""
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    ordered = base.repartitionByRange("doc_id").sortWithinPartitions("doc_id", F.xxhash64("text"))
    return ordered.mapInArrow(_write(tokenizer, end, folder), "part long, n long")


def _read(folder: str):
    def run(batches):
        for batch in batches:
            for part, base in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                file = Reader(f"{folder}/part-{part:06d}.ids")
                ends = np.append(file.starts[1:], file.total)
                k = 0
                while k < len(file.docs):  # some documents at a time, their ids in one read
                    to = max(k + 1, int(np.searchsorted(ends, file.starts[k] + (1 << 20), "right")))
                    ids = file.ids(int(file.starts[k]), int(ends[to - 1] - file.starts[k])).tobytes()
                    at = 4 * (file.starts[k:to] - file.starts[k])
                    until = 4 * (ends[k:to] - file.starts[k])
                    crc = [zlib.crc32(ids[a:b]) for a, b in zip(at.tolist(), until.tolist(), strict=True)]
                    doc = pa.array(file.docs[k:to].astype(np.int64), mask=file.docs[k:to] == NO_ID)
                    yield pa.RecordBatch.from_arrays([doc, pa.array(file.starts[k:to] + base), pa.array((until - at) // 4), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])
                    k = to
                file.close()

    return run


def digests(manifest: DataFrame, folder: str) -> DataFrame:
    """Reads the files back: doc_id, start, n_tokens, ids_crc32 per document. ``manifest`` has a row a file."""
    spark, at, plan = manifest.sparkSession, 0, []
    for part, n in sorted((r["part"], r["n"]) for r in manifest.collect()):
        plan.append((part, at))
        at += n
    files = spark.createDataFrame(plan, "part long, base long") if plan else spark.createDataFrame([], "part long, base long")
    return files.repartition(max(1, len(plan)), "part").mapInArrow(_read(folder), "doc_id long, start long, n_tokens long, ids_crc32 long")


def round_trip(docs: DataFrame, tokenizer: str, end: int = 2) -> DataFrame:
    """Encodes and writes ``docs``, then gives the digests of what the files hold."""
    scratch = Scratch(docs.sparkSession, "token-ids")
    manifest = scratch.keep(write(docs, tokenizer, scratch.path("files"), end), "manifest")
    return digests(manifest, scratch.path("files"))
