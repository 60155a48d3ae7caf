"""Language identification of mixed text: script ranges, word scores, Viterbi with a switching penalty.

Letters are what Unicode calls letters, with the marks that follow them, and are grouped by script; a word's script leaves only the languages that were seen in it. Each remaining language scores
the word by its letter 1- to 4-grams (hashed tables of log ratios, learned from labelled text). Viterbi over the words of a text
then finds the best labelling where each switch costs ``PENALTY``; runs of one label are its spans. All texts of a batch
advance together: each is cut into blocks, a block's best transitions from every state are found in lockstep, and
blocks are put together by max-plus steps, so long texts cost no more per word than short ones.

The tables are fitted on at most ``FIT_ROWS`` rows of at most ``FIT_CHARS`` characters together, drawn by a hash of their id (the documented bounds); a
row that would exceed the characters is passed over.

Defined cases: a null text, an empty text and one with no letter (digits, marks, emoji) are ``und`` with score 0; without any labelled row every text
is ``und``. Rows with a null lang are never learned from, and equal rows are learned from once. Ties go to the alphabetically first language. Rows come
back as often as they occur; other columns are ignored.
"""

from __future__ import annotations

import sys
import unicodedata
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

FIT_ROWS, FIT_CHARS = 6_000, 40_000_000
PENALTY, ORDERS, TABLE, BLOCK = 6.0, (1, 2, 3, 4), 1 << 17, 32
SLICE = 1 << 20  # characters handled at a time
# First and last code points of scripts, by public Unicode block.
SCRIPTS = (
    ("Latin", 0x41, 0x5A), ("Latin", 0x61, 0x7A), ("Latin", 0xAA, 0xAA), ("Latin", 0xBA, 0xBA), ("Latin", 0xC0, 0xD6), ("Latin", 0xD8, 0xF6), ("Latin", 0xF8, 0x2AF),
    ("Greek", 0x370, 0x3FF), ("Cyrillic", 0x400, 0x52F), ("Armenian", 0x531, 0x587), ("Hebrew", 0x5D0, 0x5EA), ("Arabic", 0x620, 0x6FF), ("Devanagari", 0x900, 0x97F),
    ("Thai", 0xE01, 0xE3A), ("Georgian", 0x10A0, 0x10FF), ("Hangul", 0x1100, 0x11FF), ("Latin", 0x1E00, 0x1EFF), ("Greek", 0x1F00, 0x1FFF), ("Kana", 0x3041, 0x30FF), ("Han", 0x3400, 0x9FFF), ("Hangul", 0xAC00, 0xD7A3),
)
SCRIPT_NAMES = ("none", *dict.fromkeys(name for name, _, _ in SCRIPTS), "other")


_MARK = len(SCRIPT_NAMES)  # belongs to the letter before it


def _script_table() -> np.ndarray:
    """Per code point: 0 no letter, the number of its script, or ``_MARK``."""
    named = np.full(sys.maxunicode + 1, len(SCRIPT_NAMES) - 1, np.uint8)
    for name, lo, hi in SCRIPTS:
        named[lo : hi + 1] = SCRIPT_NAMES.index(name)
    every = [unicodedata.category(chr(k))[0] for k in range(sys.maxunicode + 1)]
    kind = np.frombuffer("".join(every).encode(), np.uint8)
    return np.where(kind == ord("L"), named, np.where(kind == ord("M"), _MARK, 0)).astype(np.uint8)


_SCRIPT: list[np.ndarray] = []


def scripts(code: np.ndarray) -> np.ndarray:
    """Script number of each code point; 0 for what is no letter, ``_MARK`` for combining marks."""
    if not _SCRIPT:
        _SCRIPT.append(_script_table())
    return _SCRIPT[0][code]


@dataclass
class Words:
    """Runs of letters of one text slice, with the hashed n-grams that end at each letter."""

    start: np.ndarray
    end: np.ndarray
    script: np.ndarray
    grams: list[np.ndarray]  # per order: table slot at each code point
    code: np.ndarray


def letters(text: str) -> Words:
    # a blank before and after, so that a word scores the same wherever its text stands in a batch
    code = np.frombuffer((text.lower() + " ").encode("utf-32-le", "replace"), np.uint32)
    kind = scripts(code)
    letter = kind > 0
    edge = np.flatnonzero(np.diff(np.concatenate(([0], letter.view(np.int8), [0]))))
    start, end = edge[0::2], edge[1::2]
    if (kind == _MARK).any():  # a run of marks alone is no word, and the first letter names the script
        real = np.flatnonzero(letter & (kind != _MARK))
        place = np.searchsorted(real, start)
        first = np.append(real, len(code))[place]
        word = first < end
        for a, b in zip(start[~word].tolist(), end[~word].tolist(), strict=True):
            letter[a:b] = False
        start, end, first = start[word], end[word], first[word]
    else:
        first = start
    lead = max(ORDERS) - 1
    here = np.concatenate((np.full(lead, 0x20), np.where(letter, code, 0x20))).astype(np.uint64)  # all that is no letter marks a word's edge
    grams, total = [], np.zeros(len(code), np.uint64)
    for k in range(max(ORDERS)):
        total = total * np.uint64(0x100000001B3) + here[lead - k : len(here) - k] * np.uint64(0x9E3779B97F4A7C15)
        if k + 1 in ORDERS:
            h = total ^ (total >> np.uint64(29))
            grams.append(((h * np.uint64(0xBF58476D1CE4E5B9)) >> np.uint64(47)).astype(np.int64))
    return Words(start, end, kind[first] if len(start) else kind[:0], grams, code)


class Model:
    def __init__(self, langs: list[str], tables: np.ndarray, allowed: np.ndarray):
        self.langs, self.tables, self.allowed = langs, tables, allowed  # (orders, TABLE, langs) float32; (scripts, langs) bool

    def word_scores(self, w: Words) -> np.ndarray:
        """(words, langs): mean log ratio of each word's n-grams, -inf-like for languages not seen in its script."""
        if not len(w.start):
            return np.zeros((0, len(self.langs)), np.float32)
        per = np.zeros((len(w.code) + 1, len(self.langs)), np.float64)
        for table, slot in zip(self.tables, w.grams, strict=True):
            per[1:] += table[slot]
        total = np.cumsum(per, axis=0)
        # the letter after a word closes its n-grams, so it counts too where there is one
        out = (total[np.minimum(w.end + 1, len(w.code))] - total[w.start]).astype(np.float32)
        seen = self.allowed[w.script]
        return np.where(seen | ~seen.any(axis=1, keepdims=True), out, np.float32(-1e4))


def viterbi(scores: np.ndarray, penalty: float = PENALTY) -> np.ndarray:
    """Best label of each word; a switch costs ``penalty``."""
    n, k = scores.shape
    if n == 0 or k < 2:
        return np.zeros(n, np.int64)
    blocks = -(-n // BLOCK)
    s = np.zeros((blocks * BLOCK, k), np.float64)  # padding scores nothing, so it never switches
    s[:n] = scores
    s = s.reshape(blocks, BLOCK, k)
    # best[b, i, j]: best score through block b from state i before it to state j at its end
    best = np.full((blocks, k, k), -1e18)
    best[:, np.arange(k), np.arange(k)] = 0.0
    for t in range(BLOCK):
        best = np.maximum(best, best.max(axis=2, keepdims=True) - penalty) + s[:, None, t]
    # through the blocks: the state before each
    at, back = np.zeros(k), np.zeros((blocks, k), np.int64)
    for b in range(blocks):
        step = at[:, None] + best[b]
        back[b], at = step.argmax(axis=0), step.max(axis=0)
    state = np.zeros(blocks + 1, np.int64)
    state[blocks] = at.argmax()
    for b in range(blocks - 1, -1, -1):
        state[b] = back[b, state[b + 1]]
    # inside all blocks at once
    v = np.full((blocks, k), -1e18)
    v[np.arange(blocks), state[:-1]] = 0.0
    stay = np.zeros((BLOCK, blocks, k), bool)
    top = np.zeros((BLOCK, blocks), np.int64)
    for t in range(BLOCK):
        top[t] = v.argmax(axis=1)
        moved = v.max(axis=1, keepdims=True) - penalty
        stay[t] = v >= moved
        v = np.maximum(v, moved) + s[:, t]
    label, now = np.zeros((BLOCK, blocks), np.int64), state[1:].copy()
    for t in range(BLOCK - 1, -1, -1):
        label[t] = now
        now = np.where(stay[t][np.arange(blocks), now], now, top[t])
    return label.T.reshape(-1)[:n]


def _cuts(text: str) -> list[tuple[int, str]]:
    """Parts of a long text, cut at blanks where it has any."""
    out, at = [], 0
    while len(text) - at > SLICE:
        to = text.rfind(" ", at, at + SLICE) + 1 or at + SLICE
        out.append((at, text[at:to]))
        at = to
    return [*out, (at, text[at:])]


def spans(text: str | None, model: Model) -> list[tuple[int, int, str]]:
    """(start, end, lang) of the runs of one language in a whole text; characters of the lower-cased text."""
    rows, where = [], []
    for at, part in _cuts(text or ""):
        w = letters(part)
        rows.append(model.word_scores(w))
        where += list(zip((w.start + at).tolist(), (w.end + at).tolist(), strict=True))
    if not where or not model.langs:
        return []
    out: list[list] = []
    for (a, b), k in zip(where, viterbi(np.concatenate(rows)).tolist(), strict=True):
        if out and out[-1][2] == k:
            out[-1][1] = b
        else:
            out.append([a, b, k])
    return [(a, b, model.langs[k]) for a, b, k in out]


def predict(texts: list[str | None], model: Model) -> tuple[list[str], list[float]]:
    """Language with most letters after Viterbi, and its share of the letters."""
    names, shares = [], []
    group: list[int] = []
    size = 0
    out: dict[int, tuple[str, float]] = {}

    def flush() -> None:
        """One pass over the words of many texts; blocks keep them apart."""
        nonlocal size
        joined = " ".join(texts[k] for k in group)
        low = joined.lower()
        if len(low) != len(joined):  # lower-casing can add letters: each text alone then
            for k in group:
                out[k] = _one(texts[k], model)
        else:
            begin = np.cumsum([0, *(len(texts[k]) + 1 for k in group)])
            w = letters(low)
            s = model.word_scores(w)
            of = np.searchsorted(begin, w.start, "right") - 1
            first = np.searchsorted(of, np.arange(len(group) + 1))
            label = _viterbi_many(s, first)
            weight = np.zeros((len(group), len(model.langs)))
            np.add.at(weight, (of, label), (w.end - w.start).astype(float))
            for n, k in enumerate(group):
                total = weight[n].sum()
                best = int(weight[n].argmax())
                out[k] = (model.langs[best], float(weight[n, best] / total)) if total else ("und", 0.0)
        group.clear()
        size = 0

    for k, text in enumerate(texts):
        if not text or not model.langs:
            out[k] = ("und", 0.0)
        elif len(text) > SLICE:
            out[k] = _one(text, model)
        else:
            group.append(k)
            size += len(text)
            if size > SLICE:
                flush()
    if group:
        flush()
    for k in range(len(texts)):
        names.append(out[k][0])
        shares.append(out[k][1])
    return names, shares


def _one(text: str, model: Model) -> tuple[str, float]:
    rows, size = [], []
    for _, part in _cuts(text):
        w = letters(part)
        rows.append(model.word_scores(w))
        size.append(w.end - w.start)
    length = np.concatenate(size)
    if not len(length):
        return "und", 0.0
    weight = np.bincount(viterbi(np.concatenate(rows)), weights=length.astype(float), minlength=len(model.langs))
    return model.langs[int(weight.argmax())], float(weight.max() / weight.sum())


def _viterbi_many(scores: np.ndarray, first: np.ndarray, penalty: float = PENALTY) -> np.ndarray:
    """viterbi() of consecutive texts (``first``: where each begins), their blocks in one pass.

    Between texts a reset is exact: the first word of a text may take any state at no cost.
    """
    n, k = scores.shape
    if n == 0 or k < 2:
        return np.zeros(n, np.int64)
    count = np.diff(first)
    per = -(-count // BLOCK)
    base = np.concatenate(([0], np.cumsum(per)))
    blocks = int(base[-1])
    text = np.repeat(np.arange(len(count)), count)
    slot = base[text] * BLOCK + (np.arange(n) - first[text])
    s = np.zeros((blocks * BLOCK, k), np.float32)
    s[slot] = scores
    s = s.reshape(blocks, BLOCK, k)
    best = np.full((blocks, k, k), -1e18, np.float64)
    best[:, np.arange(k), np.arange(k)] = 0.0
    for t in range(BLOCK):
        best = np.maximum(best, best.max(axis=2, keepdims=True) - penalty) + s[:, None, t]
    # all texts step through their blocks together, longest first
    order = np.argsort(-per, kind="stable")
    at = np.zeros((len(count), k))
    back = np.zeros((blocks, k), np.int8)
    live = np.searchsorted(-per[order], -np.arange(1, int(per.max()) + 1), "right")
    for b, m in enumerate(live.tolist()):
        who = order[:m]
        step = at[who][:, :, None] + best[base[who] + b]
        back[base[who] + b] = step.argmax(axis=1)
        at[who] = step.max(axis=1)
    after = np.zeros(blocks, np.int64)
    now = at.argmax(axis=1)
    before = np.zeros(blocks, np.int64)
    for b in range(len(live) - 1, -1, -1):
        who = order[: live[b]]
        rows = base[who] + b
        after[rows] = now[who]
        now[who] = back[rows, now[who]]
        before[rows] = now[who]
    v = np.full((blocks, k), -1e18)
    v[np.arange(blocks), before] = 0.0
    stay, top = np.zeros((BLOCK, blocks, k), bool), np.zeros((BLOCK, blocks), np.int8)
    for t in range(BLOCK):
        top[t] = v.argmax(axis=1)
        moved = v.max(axis=1, keepdims=True) - penalty
        stay[t] = v >= moved
        v = np.maximum(v, moved) + s[:, t]
    label, every = np.zeros((BLOCK, blocks), np.int8), np.arange(blocks)
    state = after
    for t in range(BLOCK - 1, -1, -1):
        label[t] = state
        state = np.where(stay[t][every, state], state, top[t])
    return label.T.reshape(-1)[slot].astype(np.int64)


def train(texts: list[str], langs: list[str]) -> Model:
    """Tables of log ratios: an n-gram's smoothed share in a language over its mean share in all."""
    names = sorted(set(langs))
    counts = np.zeros((len(ORDERS), TABLE, len(names)))
    seen = np.zeros((len(SCRIPT_NAMES), len(names)))
    for text, lang in zip(texts, langs, strict=True):
        k = names.index(lang)
        for _, part in _cuts(text):
            w = letters(part)
            if not len(w.start):
                continue
            inside = np.zeros(len(w.code) + 2, np.int64)
            np.add.at(inside, w.start, 1)
            np.add.at(inside, w.end + 1, -1)
            mask = np.cumsum(inside)[: len(w.code)] > 0
            for order, slot in enumerate(w.grams):
                counts[order, :, k] += np.bincount(slot[mask], minlength=TABLE)
            seen[:, k] += np.bincount(w.script, minlength=len(SCRIPT_NAMES))
    tables = np.zeros(counts.shape, np.float32)
    for order in range(len(ORDERS)):
        share = (counts[order] + 0.5) / (counts[order].sum(axis=0) + 0.5 * TABLE)
        if names:
            tables[order] = np.log(share / share.mean(axis=1, keepdims=True)).clip(-4, 4) / len(ORDERS)
    return Model(names, tables, seen > 0.001 * np.maximum(1, seen.sum(axis=0)))


def fit(docs: DataFrame, held_out, rows: int = FIT_ROWS) -> Model:
    text = F.col("text").cast("string")
    known = docs.where(~held_out).select("doc_id", F.col("lang").cast("string").alias("lang"), text.alias("text"), F.xxhash64(text).alias("th")).where("lang is not null and text is not null")
    n = known.count()
    small = known.select("doc_id", "lang", "th", F.length("text").alias("size"))
    if n > 2 * rows:  # by a share first, so that few rows meet in the task that puts them in order
        small = small.where(F.pmod(F.xxhash64("doc_id", "th"), F.lit(1 << 40)) < int((1 << 40) * min(1.0, 1.5 * rows / n)))
    drawn, left = [], FIT_CHARS
    for r in small.distinct().orderBy(F.xxhash64("doc_id", "th"), "doc_id", "th", "lang").limit(rows).collect():  # bounded by `rows`
        if r["size"] <= left:
            drawn.append((r["doc_id"], r["lang"], r["th"]))
            left -= r["size"]
    if not drawn:
        return train([], [])
    chosen = F.broadcast(docs.sparkSession.createDataFrame(drawn, "doc_id long, lang string, th long"))
    got = known.join(chosen, ["doc_id", "lang", "th"]).groupBy("doc_id", "lang", "th").agg(F.first("text").alias("text")).select("lang", "text").toPandas().sort_values(["lang", "text"])
    return train(got["text"].tolist(), got["lang"].tolist())


def _labelled(handle):
    def run(batches):
        model = handle.value
        for batch in batches:
            names, shares = predict(batch.column(1).to_pylist(), model)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(names, pa.string()), pa.array(shares, pa.float64())], ["doc_id", "lang_pred", "score"])

    return run


def identify(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, lang_pred, score; learned outside crc32(doc_id) mod 3 = 1."""
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 3 == 1, F.lit(False))
    model = fit(docs, held)
    handle = docs.sparkSession.sparkContext.broadcast(model)  # tables of a fixed size for each language
    out = docs.select("doc_id", F.col("text").cast("string").alias("text")).mapInArrow(_labelled(handle), "doc_id long, lang_pred string, score double")
    return out.select("doc_id", held.alias("held_out"), "lang_pred", "score")
