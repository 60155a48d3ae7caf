"""Substring dedup by hashed lines, and by content-cut pieces of lines.

Each line is a unit, normalised to its blank-separated lower-cased words. Passages that documents share are often spliced into
lines that differ, where whole lines never match; so lines are cut further, at words whose hash is the smallest among its neighbours
(the same words are cut alike wherever they stand), and the pieces are units too. Few or long pieces can leave a passage without enough whole
ones, so windows of ``WINDOW`` words are the third kind: of each ``PASSAGE - WINDOW + 1`` neighbours the one with the smallest hash, whatever the
lines. So every passage of ``PASSAGE`` words holds a window that is drawn in all its copies. Digests of all units are grouped globally; the
occurrence with the smallest (doc_id, text digest, position) is kept. Removed are later whole lines of at least ``line_words`` words, and runs of
words in later pieces or windows, of at least ``run_words`` words. Removed spans are given as byte offsets of the original UTF-8 text.

Defined cases: null and empty texts have no units and stay as they are; a null doc_id takes no part. Rows that repeat a doc_id and its
text count as one document, so they never remove each other; a doc_id with several texts is as many documents, ranked by the digests of their
texts. A unit that repeats within a document is kept once. Ties cannot occur, as positions differ. All other columns pass through, whatever their
names; one that is named like ``spans_col`` gives way to it. An empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, LongType, StringType, StructField, StructType

from . import words
from .common import Scratch, lean, quoted

LINE_WORDS, RUN_WORDS, REACH = 10, 25, 4
WINDOW, PASSAGE = 25, 51
OFTEN = 10_000  # occurrences from which a unit may count as frequent
SLICE = 1 << 21  # bytes of texts taken in one pass
_SEED = np.uint64(0x2545F4914F6CDD1D)


def _sums(values: np.ndarray, start: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        return np.add.reduceat(values, start) if len(start) else values[:0]


def _windows(hashed: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, ...]:
    """First word, digest and check of the drawn windows; no window reaches over the end of a document."""
    n = len(hashed)
    if n < PASSAGE:
        zero = np.zeros(0, np.int64)
        return zero, zero.view(np.uint64), zero
    up, down = words._power_tables(n + 1)
    digests = []
    for values in (hashed, words.mix(hashed ^ _SEED)):
        total = np.zeros(n + 1, np.uint64)
        with np.errstate(over="ignore"):
            np.cumsum(values * up[:n], out=total[1:])
            digests.append(words.mix((total[WINDOW:] - total[:-WINDOW]) * down[: n - WINDOW + 1]))
    span = PASSAGE - WINDOW + 1
    whole = np.flatnonzero(doc[: n - PASSAGE + 1] == doc[PASSAGE - 1 :])  # passages inside one document
    low = np.lib.stride_tricks.sliding_window_view(digests[0], span)[whole].argmin(axis=1)
    first = np.unique(low + whole)
    return first, digests[0][first] ^ _SEED, (digests[1][first] >> np.uint64(33)).astype(np.int64)


@dataclass
class Units:
    """Units of several texts, by text, then kind (0 line, 1 piece, 2 window), each in order; ``place`` counts them within a text and kind."""

    doc: np.ndarray
    kind: np.ndarray
    place: np.ndarray
    digest: np.ndarray
    check: np.ndarray
    size: np.ndarray
    word: np.ndarray  # first word, counted over all texts
    start: np.ndarray  # of each word: first byte and end byte in its text
    end: np.ndarray
    first: np.ndarray  # each text's first word, and the number of all


def units(texts: list[bytes]) -> Units:
    """All texts in one pass over their joined words, as most are short."""
    joined = b"\n".join(texts)
    hashed, start, end = words.word_hashes(joined)
    n, many = len(hashed), len(texts)
    begin = np.cumsum([0, *(len(t) + 1 for t in texts)])
    doc = np.searchsorted(begin, start, "right") - 1
    word_of = np.searchsorted(doc, np.arange(many + 1))
    if not n:
        zero = np.zeros(0, np.int64)
        return Units(zero, zero, zero, zero.view(np.uint64), zero, zero, zero, zero, zero, word_of)
    line = np.searchsorted(np.flatnonzero(np.frombuffer(joined, np.uint8) == 10), start)
    head = np.concatenate(([True], line[1:] != line[:-1]))
    # a piece begins at a local minimum of the hashes of word pairs, which see one word on each side of the cut
    pair = words.mix(hashed ^ _SEED)
    low = np.ones(n, bool)
    for k in range(1, min(REACH, n - 1) + 1):
        low[k:] &= pair[k:] <= pair[:-k]
        low[:-k] &= pair[:-k] < pair[k:]
    inside = np.arange(n) - word_of[doc]
    low &= (inside >= REACH) & (inside < (word_of[doc + 1] - word_of[doc]) - REACH)  # so that no text sees another
    out = []
    for kind, first in ((0, np.flatnonzero(head)), (1, np.flatnonzero(head | low))):
        size = np.diff(np.append(first, n))
        at = np.arange(n) - np.repeat(first, size)
        with np.errstate(over="ignore"):
            spread = words.mix(np.uint64(2 * kind + 1) + at.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
            digest = words.mix(_sums(hashed * (spread | np.uint64(1)), first) + size.astype(np.uint64))
            check = words.mix(_sums(words.mix(hashed + spread), first)) >> np.uint64(33)
        out.append((np.full(len(first), kind), digest, check.astype(np.int64), size, first))
    first, digest, check = _windows(hashed, doc)
    out.append((np.full(len(first), 2), digest, check, np.full(len(first), WINDOW), first))
    kind, digest, check, size, first = (np.concatenate(x) for x in zip(*out, strict=True))
    order = np.argsort(doc[first] * 3 + kind, kind="stable")
    kind, digest, check, size, first = (x[order] for x in (kind, digest, check, size, first))
    group = doc[first] * 3 + kind
    return Units(doc[first], kind, np.arange(len(kind)) - np.searchsorted(group, group), digest, check, size, first, start - begin[doc], end - begin[doc], word_of)


def _slices(texts: list[bytes | None]):
    """(first, end) of runs of texts of bounded size; one long text is a run of its own."""
    at = 0
    while at < len(texts):
        to, held = at, 0
        while to < len(texts) and (to == at or held + len(texts[to] or b"") < SLICE):
            held += len(texts[to] or b"")
            to += 1
        yield at, to
        at = to


def _rows(line_words: int):
    """Units that may be removed: lines that are too short to go are left out."""

    def run(batches):
        for batch in batches:
            docs, tags = (batch.column(k).to_numpy(zero_copy_only=False) for k in (0, 2))
            texts = words.text_bytes(batch.column(1))
            for a, b in _slices(texts):
                u = units(texts[a:b])
                keep = np.flatnonzero((u.kind > 0) | (u.size >= line_words))
                row = u.doc[keep] + a
                columns = (docs[row], tags[row], u.digest[keep].view(np.int64), u.check[keep].astype(np.int32), 3 * u.place[keep] + u.kind[keep])
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], ["doc_id", "tag", "digest", "check", "place"])

    return run


def removed_spans(texts: list[bytes], again: list[list[int]], line_words: int, run_words: int) -> list[list[tuple[int, int]]]:
    """Byte spans to cut from each text, given the places of its units that stand earlier elsewhere."""
    u = units(texts)
    begin = np.searchsorted(u.doc * 3 + u.kind, np.arange(3 * len(texts) + 1))
    spot = np.concatenate([np.asarray(p, np.int64) for p in again]) if again else np.zeros(0, np.int64)
    of = np.repeat(np.arange(len(texts)), [len(p) for p in again])
    flag = np.zeros(len(u.kind), bool)
    group = 3 * of + spot % 3
    spot = spot // 3 + begin[group]
    flag[spot[spot < begin[group + 1]]] = True
    out = []
    for d, text in enumerate(texts):
        line, piece, window = (slice(begin[3 * d + k], begin[3 * d + k + 1]) for k in range(3))
        base, gone = u.first[d], []
        # whole lines go with the line break before or after them
        for k in (np.flatnonzero(flag[line] & (u.size[line] >= line_words)) + line.start).tolist():
            gone.append((int(u.start[u.word[k]]), int(u.end[u.word[k] + u.size[k] - 1])))
        drawn = flag[window]
        if drawn.any() or int(u.size[piece][flag[piece]].sum()) >= run_words:
            again_word = np.repeat(flag[piece], u.size[piece])
            if drawn.any():
                # windows overlap: the words of a kept one stay, if its later copies stand in the same text
                digest, word = u.digest[window], u.word[window] - base
                first = ~drawn & np.isin(digest, digest[drawn])
                kept_word = np.zeros(len(again_word), bool)
                for mask, which in ((kept_word, first), (again_word, drawn)):
                    for k in word[which].tolist():
                        mask[k : k + WINDOW] = True
                again_word &= ~kept_word
            edge = np.flatnonzero(np.diff(np.concatenate(([0], again_word.view(np.int8), [0]))))
            for a, b in zip(edge[0::2].tolist(), edge[1::2].tolist(), strict=True):
                if b - a >= run_words:
                    gone.append((int(u.start[base + a]), int(u.end[base + b - 1])))
        out.append(_merged(text, gone) if gone else [])
    return out


def _merged(text: bytes, gone: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Spans put together where only blanks lie between, with the blanks and line breaks that would be left over."""
    merged: list[list[int]] = []
    for a, b in sorted(gone):
        if merged and (a <= merged[-1][1] or not text[merged[-1][1] : a].strip()):
            merged[-1][1] = max(merged[-1][1], b)
        else:
            merged.append([a, b])
    out = []
    for a, b in merged:
        while b < len(text) and text[b] in b" \t\r\x0b\x0c":
            b += 1
        opens = a == 0 or text[a - 1] == 10
        if opens and b < len(text) and text[b] == 10:
            b += 1
        elif opens and b == len(text) and a:
            a -= 1
        out.append((a, b))
    return out


def _cut(line_words: int, run_words: int):
    def run(batches):
        for batch in batches:
            n, names = batch.num_columns, batch.schema.names
            texts, again = words.text_bytes(batch.column(n - 2)), batch.column(n - 1).to_pylist()
            new, spans = list(texts), [[] for _ in texts]
            some = [k for k in range(len(texts)) if texts[k] and again[k]]
            for a, b in _slices([texts[k] for k in some]):
                part = some[a:b]
                for k, cut in zip(part, removed_spans([texts[k] for k in part], [again[k] for k in part], line_words, run_words), strict=True):
                    if cut:
                        text, keep, at = texts[k], [], 0
                        for x, y in cut:
                            keep.append(text[at:x])
                            at = y
                        new[k], spans[k] = b"".join([*keep, text[at:]]), [{"start": x, "end": y} for x, y in cut]
            new = [None if x is None else x.decode("utf-8", "replace") for x in new]
            kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
            yield pa.RecordBatch.from_arrays([*batch.columns[: n - 2], pa.array(new, pa.string()), pa.array(spans, kind)], [*names[: n - 2], "text", "spans"])

    return run


def dedup_units(docs: DataFrame, line_words: int = LINE_WORDS, run_words: int = RUN_WORDS, id_col: str = "doc_id", text_col: str = "text", spans_col: str = "removed") -> DataFrame:
    """``docs`` with shortened texts, and ``spans_col``: array of (start, end) byte offsets cut from the original."""
    scratch = Scratch(docs.sparkSession, "substring")
    named = [c for c in docs.columns if c != spans_col]
    text = docs[quoted(text_col)].cast("string")
    # a row goes by its id and its text's digest, as an id may have several texts
    base = docs.select(docs[quoted(id_col)].cast("long").alias("doc_id"), text.alias("text"), F.xxhash64(text).alias("tag")).where("doc_id is not null and text <> ''")

    def found() -> DataFrame:
        return base.mapInArrow(lean(_rows(line_words)), "doc_id long, tag long, digest long, check int, place long")

    first = F.min(F.struct("doc_id", "tag", "place"))
    kept = found().groupBy("digest", "check").agg(first.alias("first"), F.count("*").alias("n")).where("n > 1")
    kept = scratch.keep(kept.select("digest", "check", F.col("first.doc_id").alias("at_doc"), F.col("first.tag").alias("at_tag"), F.col("first.place").alias("at"), "n"), "kept")
    # units that a hundred-thousandth of all repeats or more fall on are at most 100,000, so they are broadcast; their occurrences then
    # travel under keys of their own, and no task gathers those of one line
    repeats = kept.agg(F.sum("n")).first()[0] or 0
    often = kept.where(F.col("n") >= max(OFTEN, repeats // 100_000)).select("digest", "check", F.struct("at_doc", "at_tag", "at").alias("hot"))
    spread = found().join(F.broadcast(often), ["digest", "check"], "left")
    spread = spread.withColumn("digest", F.when(F.col("hot").isNotNull(), F.xxhash64("doc_id", "tag", "place")).otherwise(F.col("digest")))
    rare = kept.select("digest", "check", F.struct("at_doc", "at_tag", "at").alias("cold"))
    met = spread.join(rare, ["digest", "check"], "left").withColumn("kept", F.coalesce("hot", "cold"))
    later = met.where("kept is not null").where("doc_id <> kept.at_doc or tag <> kept.at_tag or place <> kept.at")
    again = scratch.keep(later.groupBy("doc_id", "tag").agg(F.collect_set("place").alias("places")), "again")
    scratch.drop("kept")
    # the other columns travel in one struct, so that no name can clash
    others = [F.col(quoted(c)) for c in named if c != text_col]
    whole = docs.select(F.struct(*others).alias("others"), F.col(quoted(id_col)).cast("long").alias("doc_id"), F.col(quoted(text_col)).cast("string").alias("text"))
    joined = whole.withColumn("tag", F.xxhash64("text")).join(again, ["doc_id", "tag"], "left").select("others", "text", "places")
    span = StructType([StructField("start", LongType()), StructField("end", LongType())])
    cut = joined.mapInArrow(lean(_cut(line_words, run_words)), StructType([joined.schema["others"], StructField("text", StringType()), StructField("spans", ArrayType(span))]))
    return cut.select(*[F.col("text").alias(c) if c == text_col else F.col("others")[c].alias(c) for c in named], F.col("spans").alias(spans_col))
