"""Benchmark decontamination: word-pair seeds, then Smith-Waterman alignment of words.

One pass over the corpus without a shuffle of text. All word pairs of a test item are seeds, however frequent they are in the corpus: a
count of documents would hold the leaks themselves. A stretch of a document is aligned with an item, word by word, if it holds as many of the item's
pairs as an alignment at the cut must have (``needed``); the score is the alignment's, over that of a full match. So edited or
reordered copies are found as well as exact ones: every copy at the cut whose words were changed or dropped, and those with words
put in, unless these split about four in five of the item's pairs.

Items reach the executors in slices of at most ``SLICE_CHARS`` characters; a larger benchmark takes more passes.

Defined cases: null texts and items, and those without a word, match nothing. Items of under three words are sought whole, and longer ones need two
pairs. Repeated rows give repeated pairs; items with equal text are each reported. Words are runs of letters and digits, lower-cased in ASCII. Empty
tables give no rows; other columns are ignored.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import words
from .common import lean

SEED_WORDS, CUT, SLICE_CHARS = 2, 0.4, 16_000_000
MATCH, MISMATCH, GAP = 2, -1, -1


def needed(n: int, cut: float) -> int:
    """How many pairs of an item of n words an alignment at the cut holds at least.

    With p pairs in r runs of matches between changed or dropped words, the score is at most 2p + r + 1, and p + 2r - 1 <= n.
    """
    return max(2 if n > SEED_WORDS else 1, math.ceil(((2 * cut - 0.5) * n - 1.5) / 1.5 - 1e-9))


class Seeds:
    """Sorted n-grams of a slice's items, each with the items that hold it and how often."""

    def __init__(self, items: list[tuple[int, bytes]], cut: float = CUT):
        self.items = [(i, words.word_hashes(t, words.MARKS)[0]) for i, t in items]
        self.reach = np.array([len(w) + len(w) // 2 for _, w in self.items], np.int64)
        self.need = np.array([needed(len(w), cut) for _, w in self.items], np.int64)
        runs: dict[int, list[tuple[np.ndarray, ...]]] = {}
        for k, (_, w) in enumerate(self.items):
            n = min(SEED_WORDS, len(w))
            if n:
                g, times = np.unique(words.ngrams(w, n), return_counts=True)
                runs.setdefault(n, []).append((g, np.full(len(g), k), times))
        self.by_size, self.maybe = {}, {}
        for n, found in runs.items():
            g, owner, times = (np.concatenate(x) for x in zip(*found, strict=True))
            order = np.argsort(g, kind="stable")
            self.by_size[n] = (g[order], owner[order], times[order])
            bits = np.zeros(1 << 20, bool)
            bits[(g >> np.uint64(44)).astype(np.int64)] = True
            self.maybe[n] = bits

    def hits(self, hashed: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
        """Word positions where a run of the slice starts, and its first place in the sorted runs."""
        g = self.by_size[n][0]
        grams = words.ngrams(hashed, n)
        at = np.flatnonzero(self.maybe[n][(grams >> np.uint64(44)).astype(np.int64)])
        place = np.searchsorted(g, grams[at])
        real = (place < len(g)) & (g[np.minimum(place, len(g) - 1)] == grams[at])
        return at[real], place[real]

    def stretches(self, hashed: np.ndarray, n: int) -> list[tuple[int, int, int]]:
        """(item number, first and last position) of hits close together that hold enough of an item's runs."""
        g, owner, times = self.by_size[n]
        at, place = self.hits(hashed, n)
        if not len(at):
            return []
        many = np.searchsorted(g, g[place], "right") - place
        each = np.repeat(place, many) + np.arange(int(many.sum())) - np.repeat(np.cumsum(many) - many, many)
        at, item = np.repeat(at, many), owner[each]
        order = np.lexsort((at, item))
        at, item, each = at[order], item[order], each[order]
        # only where hits stand dense enough, counting repeats; then each run counts as often as the item holds it
        key = item * (len(hashed) + 4 * int(self.reach.max()) + 1) + at
        upto = np.concatenate(([0], np.cumsum(times[each])))
        to = np.searchsorted(key, key + 2 * self.reach[item], "right")
        dense = np.flatnonzero(upto[to] - upto[:-1] >= self.need[item])
        step = np.zeros(len(at) + 1, np.int64)
        np.add.at(step, dense, 1)
        np.add.at(step, to[dense], -1)
        live = np.cumsum(step[:-1]) > 0
        at, item, each = at[live], item[live], each[live]
        if not len(at):
            return []
        head = np.concatenate(([True], (item[1:] != item[:-1]) | (at[1:] - at[:-1] > self.reach[item[1:]])))
        group = np.cumsum(head) - 1
        once = np.unique(group * len(g) + each)
        held = np.bincount(once // len(g), times[once % len(g)], int(group[-1]) + 1)
        first = np.flatnonzero(head)
        last = np.append(first[1:], len(at)) - 1
        enough = held >= self.need[item[first]]
        return list(zip(item[first][enough].tolist(), at[first][enough].tolist(), at[last][enough].tolist(), strict=True))


def align(item: np.ndarray, window: np.ndarray) -> tuple[float, int, int]:
    """Smith-Waterman over words: score as a share of a full match, and the window's aligned span."""
    cols = np.arange(len(window) + 1)
    row, origin = np.zeros(len(window) + 1, np.int64), cols.copy()
    best = (0, 0, 0)
    for word in item:
        step = np.where(window == word, MATCH, MISMATCH)
        diagonal, up = row[:-1] + step, row[1:] + GAP
        cell, start = np.zeros_like(row), cols.copy()
        up_wins = up > diagonal
        cell[1:] = np.maximum(np.maximum(diagonal, up), 0)
        start[1:] = np.where(cell[1:] > 0, np.where(up_wins, origin[1:], origin[:-1]), cols[1:])
        # gaps along the row: a running maximum of what each cell gives to those after it
        lifted = cell - GAP * cols
        top = np.maximum.accumulate(lifted)
        giver = np.maximum.accumulate(np.where(lifted == top, cols, 0))
        origin = start[giver]
        row = np.maximum(top + GAP * cols, 0)
        k = int(row.argmax())
        if row[k] > best[0]:
            best = (int(row[k]), int(origin[k]), k)
    return best[0] / (MATCH * len(item)), best[1], best[2]


def matches(text: bytes | None, seeds: Seeds, cut: float) -> list[tuple[int, float, int, int]]:
    """(item number, score, start byte, end byte) of the best alignment of each item found in a whole text."""
    hashed, start, end = words.word_hashes(text or b"", words.MARKS)
    best: dict[int, tuple[float, int, int]] = {}
    for n in seeds.by_size:
        for k, first, last in seeds.stretches(hashed, n):
            reach = int(seeds.reach[k])
            lo, hi = max(0, first - reach), last + SEED_WORDS + reach
            score, a, b = align(seeds.items[k][1], hashed[lo:hi])
            if score >= cut and score > best.get(k, (0.0,))[0]:
                best[k] = (score, int(start[lo + a]), int(end[lo + b - 1]))
    return [(k, *v) for k, v in best.items()]


def _aligned(handle, cut: float):
    def run(batches):
        seeds: Seeds = handle.value
        for batch in batches:
            rows = []
            for doc, text in zip(batch.column(0).to_pylist(), words.text_bytes(batch.column(1)), strict=True):
                rows += [(doc, seeds.items[k][0], score, a, b) for k, score, a, b in matches(text, seeds, cut)]
            kinds = (pa.int64(), pa.int64(), pa.float64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate(kinds)], ["doc_id", "item_id", "score", "start", "end"])

    return run


def contaminated(docs: DataFrame, benchmark: DataFrame, cut: float = CUT) -> DataFrame:
    """doc_id, item_id, score, start, end (bytes) of each document that holds a copy of an item, edited or not."""
    spark = docs.sparkSession
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where("text is not null")
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).where("text is not null")
    chars = items.agg(F.sum(F.length("text"))).first()[0] or 0
    slices, out = max(1, -(-chars // SLICE_CHARS)), None
    for k in range(slices):  # one slice unless the benchmark is very large
        part = items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(slices)) == k).orderBy("item_id", "text").collect()
        seeds = spark.sparkContext.broadcast(Seeds([(r["item_id"], r["text"].encode()) for r in part], cut))
        found = base.mapInArrow(lean(_aligned(seeds, cut)), "doc_id long, item_id long, score double, start long, end long")
        out = found if out is None else out.unionByName(found)
    return out
