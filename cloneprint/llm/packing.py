"""Packing by best-fit decreasing, over counts of piece lengths.

A document's ids (with the end id) are cut into full windows and a rest. Pieces of one
length are alike, so best-fit decreasing needs only how many there are of each length: at most
``window`` counts, however large the corpus. The driver runs it on them with a segment tree indexed by
remaining capacity, where windows of equal capacity lie as ranges of numbers, and gets rules ("pieces
r0..r1 of length L fill windows w0.. from offset o"). Executors number the pieces of each length
and apply the rules. No window or piece is ever gathered.

Defined cases: a null or empty text is a document of the end id alone; null doc_ids and
repeated rows are packed like others. Equal pieces are interchangeable (ties fall by partition and order in it).
An empty table gives no rows. Other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, lean
from .encode import encoder, forget

WINDOW, END = 1024, 0
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, part long, rank long"
RULES = "length long, lo long, hi long, per long, seq long, at long"


class CapacityTree:
    """Leftmost capacity at or above a bound that has open windows."""

    def __init__(self, window: int):
        self.size = 1 << (window + 1).bit_length()
        self.any = [False] * (2 * self.size)

    def set(self, capacity: int, has: bool) -> None:
        k = capacity + self.size
        self.any[k] = has
        while k > 1:
            k //= 2
            self.any[k] = self.any[2 * k] or self.any[2 * k + 1]

    def first(self, bound: int) -> int | None:
        k = bound + self.size
        while not self.any[k]:
            while k & 1:  # up, until there is a right sibling
                k >>= 1
                if k <= 1:
                    return None
            k += 1
        while k < self.size:
            k *= 2
            if not self.any[k]:
                k += 1
        return k - self.size


def best_fit_decreasing(counts: dict[int, int], window: int = WINDOW) -> tuple[list[tuple[int, int, int, int, int, int]], int]:
    """Rules (length, lo, hi, per window, first window, offset) and the number of windows."""
    tree, free, rules, opened = CapacityTree(window), defaultdict(list), [], 0

    def put(capacity: int, first: int, n: int) -> None:
        if n:
            free[capacity].append((first, n))
            tree.set(capacity, True)

    for length in sorted(counts, reverse=True):
        left, lo = counts[length], 0
        while left:
            capacity = tree.first(length)
            if capacity is None:
                n = -(-left // (window // length))
                put(window, opened, n)
                opened += n
                continue
            first, n = free[capacity].pop()
            if not free[capacity]:
                tree.set(capacity, False)
            # the tightest window stays the tightest until the length no longer fits
            per = capacity // length
            full = min(n, left // per)
            if full:
                rules.append((length, lo, lo + full * per, per, first, window - capacity))
                put(capacity - per * length, first, full)
                lo, left = lo + full * per, left - full * per
            if n > full and 0 < left < per:
                rules.append((length, lo, lo + left, left, first + full, window - capacity))
                put(capacity - left * length, first + full, 1)
                full, left = full + 1, 0
            put(capacity, first + full, n - full)
    return rules, opened


def _pieces(path: str, window: int, end: int):
    tail = np.array([end], "<u4").tobytes()

    def run(batches):
        from pyspark import TaskContext

        part, seen, enc = TaskContext.get().partitionId(), Counter(), encoder(path)
        try:
            for batch in batches:
                ids = batch.column(0).to_pylist()
                for at in range(0, len(ids), 256):
                    rows = []
                    for doc, got in zip(ids[at : at + 256], enc.ids([t or "" for t in batch.column(1)[at : at + 256].to_pylist()]), strict=True):
                        got += tail
                        n = len(got) // 4
                        for k in range(0, n, window):
                            length = min(window, n - k)
                            rows.append((doc, k, length, zlib.crc32(got[4 * k : 4 * (k + length)]), n, part, seen[length]))
                            seen[length] += 1
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], [f.split()[0] for f in PIECES.split(", ")])
        finally:
            forget()

    return run


def pack(docs: DataFrame, tokenizer: str, window: int = WINDOW, end: int = END, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """A row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""
    spark, scratch = docs.sparkSession, Scratch(docs.sparkSession, "packing")
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    pieces = scratch.keep(base.mapInArrow(lean(_pieces(tokenizer, window, end)), PIECES), "pieces")
    # where each partition's pieces of a length begin among all of that length
    counts = pieces.groupBy("length", "part").agg(F.count("*").alias("n"))
    begin = F.expr("sum(n) over (partition by length order by part rows between unbounded preceding and current row) - n").alias("begin")
    begins = scratch.keep(counts.select("length", "part", "n", begin), "begins")
    totals = {r["length"]: r["n"] for r in begins.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most `window` rows
    rules, _ = best_fit_decreasing(totals, window)
    rule = spark.createDataFrame(rules, RULES) if rules else spark.createDataFrame([], RULES)
    placed = pieces.join(begins.drop("n"), ["length", "part"]).withColumn("rank", F.col("rank") + F.col("begin"))
    # the rules' number is bounded by the window length, not by the data
    out = placed.join(F.broadcast(rule.withColumnRenamed("length", "of")), (F.col("length") == F.col("of")) & (F.col("rank") >= F.col("lo")) & (F.col("rank") < F.col("hi")))
    seq = F.col("seq") + F.expr("(rank - lo) div per")
    offset = F.col("at") + F.expr("(rank - lo) % per") * F.col("length")
    return out.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", seq.alias("sequence_id"), offset.alias("offset"))
