"""Token ids of whole texts with the tokenizers library, with a memo of blank-led chunks.

A byte-level BPE with the usual split pattern always ends a piece before a single blank that
follows a non-blank, so a text's ids are the ids of its chunks (a blank and what follows up to the next
blank) put together. Each distinct chunk goes through the library once and is remembered, up to a bound. Texts
where that does not hold (runs of blanks, strings of added tokens) and tokenizers of another kind go through it whole.

Texts of Latin letters, digits, marks other than the apostrophe, and single blanks or line breaks (most of the data) take a quicker road
to the same pieces: byte classes give the piece ends in numpy, and a table by piece hash gives the ids of pieces seen before.
"""

from __future__ import annotations

import json
import os
import re
import struct

import numpy as np

from .words import mix

MEMO = 250_000  # chunks, and pieces, remembered by a worker; as many again from before
LONGEST = 1 << 17  # characters encoded at once; longer texts are cut where a piece ends anyway
_SAFE_CUT = re.compile(r"(?<=\S) (?=\S)")
_loaded: dict[str, Encoder] = {}


class Memo:
    """A bounded dictionary: when it is full it becomes the old half, and what is used again moves to the new one."""

    def __init__(self, limit: int):
        self.limit, self.new, self.old = limit, {}, {}

    def get(self, key: str) -> bytes | None:
        value = self.new.get(key)
        if value is None and (value := self.old.get(key)) is not None:
            self.put(key, value)
        return value

    def put(self, key: str, value: bytes) -> None:
        if len(self.new) >= self.limit:
            self.old, self.new = self.new, {}
        self.new[key] = value


_LETTER, _DIGIT, _MARK, _SPACE, _BREAK, _OTHER = range(6)
_CLASS = np.full(256, _OTHER, np.uint8)
_CLASS[33:127] = _MARK
_CLASS[39] = _OTHER  # an apostrophe may begin a contraction
_CLASS[48:58] = _DIGIT
_CLASS[65:91] = _CLASS[97:123] = _CLASS[128:192] = _CLASS[[0xC3, 0xC4, 0xC5]] = _LETTER
_CLASS[32], _CLASS[10] = _SPACE, _BREAK
_VALUE = np.random.default_rng(5).integers(1, 1 << 63, 256, dtype=np.uint64)
_SLOTS, _POOL, GROUP = 20, 1 << 22, 1 << 19  # bits of the table's size; ids it may hold; bytes encoded at once


def _visible_bytes() -> list[str]:
    """The characters that stand for bytes in a byte-level vocabulary: printable ones for themselves, the rest from 256 on."""
    shown = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174]
    rest = iter(range(256, 512))
    return [chr(b) if b in shown else chr(next(rest)) for b in range(256)]


class PieceTable:
    """Ids of pieces by a 64-bit hash, in a table where a new piece replaces the one in its slot."""

    def __init__(self, model):
        self.model, self.shown = model, dict(enumerate(_visible_bytes()))
        self.key = np.zeros(1 << _SLOTS, np.uint64)
        self.place, self.count = np.zeros(1 << _SLOTS, np.int32), np.zeros(1 << _SLOTS, np.int32)
        self.pool, self.used = np.zeros(_POOL, np.uint32), 0
        base = np.full(GROUP * 2, 0x9E3779B97F4A7C15, np.uint64)
        back = np.full(GROUP * 2, pow(0x9E3779B97F4A7C15, -1, 1 << 64), np.uint64)
        base[0] = back[0] = 1
        self.up, self.down = np.cumprod(base, dtype=np.uint64), np.cumprod(back, dtype=np.uint64)

    def _add(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        found = [[t.id for t in self.model.tokenize(p.decode("latin-1").translate(self.shown))] for p in pieces]
        count = np.array([len(f) for f in found], np.int32)
        flat = np.array([i for f in found for i in f], np.uint32)
        if self.used + len(flat) > len(self.pool):  # start over: the table is a memo, nothing is lost
            self.key[:] = 0
            self.used = 0
            self.pool = np.zeros(max(_POOL, 2 * len(flat)), np.uint32)
        place = (self.used + np.cumsum(count) - count).astype(np.int32)
        self.pool[self.used : self.used + len(flat)] = flat
        self.used += len(flat)
        return place, count

    def ids(self, texts: list[bytes]) -> list[bytes | None]:
        """Ids of each text; None for one that needs the other road. The texts hold at most 2 * GROUP bytes."""
        size = np.array([len(t) for t in texts])
        begin = np.concatenate(([0], np.cumsum(size)))
        raw = np.frombuffer(b"".join(texts), np.uint8)
        if not len(raw):
            return [b""] * len(texts)
        kind = _CLASS[raw]
        blank = kind >= _SPACE
        odd = np.flatnonzero((kind[1:] == _OTHER) | (blank[1:] & blank[:-1]) | ((raw[:-1] == 0xC3) & ((raw[1:] == 0x97) | (raw[1:] == 0xB7)))) + 1
        simple = np.ones(len(texts), bool)
        simple[np.searchsorted(begin, odd, "right") - 1] = False  # also a text that begins with a blank after one that ends so: it is safe there too
        if kind[0] == _OTHER:
            simple[np.searchsorted(begin, 0, "right") - 1] = False
        head = np.ones(len(raw), bool)
        head[1:] = blank[1:] | (kind[:-1] == _BREAK) | ((kind[1:] != kind[:-1]) & (kind[:-1] != _SPACE))
        head[begin[:-1][size > 0]] = True
        start = np.flatnonzero(head)
        end = np.append(start[1:], len(raw))
        with np.errstate(over="ignore"):
            total = np.zeros(len(raw) + 1, np.uint64)
            np.cumsum(_VALUE[raw] * self.up[: len(raw)], out=total[1:])
            hashed = mix((total[end] - total[start]) * self.down[start] + (end - start).astype(np.uint64)) | np.uint64(1)
        slot = (hashed >> np.uint64(64 - _SLOTS)).astype(np.int64)
        keep = simple[np.searchsorted(begin, start, "right") - 1]
        lost = np.flatnonzero((self.key[slot] != hashed) & keep)
        if len(lost):
            new, first, which = np.unique(hashed[lost], return_index=True, return_inverse=True)
            if self.used + 2 * int((end - start)[lost[first]].sum()) > len(self.pool):
                self.key[:] = 0
                self.used, lost = 0, np.flatnonzero(keep)
                new, first, which = np.unique(hashed[lost], return_index=True, return_inverse=True)
            at = lost[first]
            place, count = self._add([raw[a:b].tobytes() for a, b in zip(start[at], end[at], strict=True)])
            s = slot[at]
            self.key[s], self.place[s], self.count[s] = new, place, count
        here, many = self.place[slot].astype(np.int64), np.where(keep, self.count[slot], 0).astype(np.int64)
        if len(lost):
            here[lost], many[lost] = place[which], count[which]
        # pieces that were hits may have lost their slot to a new one just now
        again = np.flatnonzero((self.key[slot] != hashed) & keep)
        if len(lost):
            again = np.setdiff1d(again, lost, assume_unique=True)
        if len(again):
            new, first, which = np.unique(hashed[again], return_index=True, return_inverse=True)
            at = again[first]
            place, count = self._add([raw[a:b].tobytes() for a, b in zip(start[at], end[at], strict=True)])
            here[again], many[again] = place[which], count[which]
        upto = np.cumsum(many)
        out = self.pool[np.repeat(here - (upto - many), many) + np.arange(int(upto[-1]))].astype("<u4", copy=False)
        upto = np.concatenate(([0], upto))
        cut = upto[np.searchsorted(start, begin)]
        data = out.tobytes()
        return [data[4 * a : 4 * b] if ok else None for a, b, ok in zip(cut[:-1].tolist(), cut[1:].tolist(), simple.tolist(), strict=True)]


class Encoder:
    """ids(texts) gives each text's ids as little-endian unsigned 32-bit bytes."""

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        spec = json.loads(self.tokenizer.to_str())
        pre, model = spec.get("pre_tokenizer") or {}, spec["model"]
        self.added = [t["content"] for t in spec.get("added_tokens", [])]
        byte_level = pre.get("type") == "ByteLevel" and pre.get("use_regex", True) and not pre.get("add_prefix_space")
        plain = spec.get("normalizer") is None and model.get("type") == "BPE" and not model.get("dropout")
        self.chunked = byte_level and plain and not any(" " in t for t in self.added)
        self.size = self.tokenizer.get_vocab_size()
        self.split, self.model = self.tokenizer.pre_tokenizer, self.tokenizer.model
        self.chunks, self.pieces = Memo(MEMO), Memo(MEMO)
        self.table = PieceTable(self.model) if self.chunked else None

    def _library(self, texts: list[str]) -> list[bytes]:
        return [np.asarray(e.ids, "<u4").tobytes() for e in self.tokenizer.encode_batch(texts, add_special_tokens=False)]

    def _chunk(self, chunk: str) -> bytes:
        """A chunk through the library's own pre-tokenizer and model, without its per-text overhead."""
        out = []
        for piece, _ in self.split.pre_tokenize_str(chunk):
            ids = self.pieces.get(piece)
            if ids is None:
                found = [t.id for t in self.model.tokenize(piece)]
                ids = struct.pack(f"<{len(found)}I", *found)
                self.pieces.put(piece, ids)
            out.append(ids)
        return b"".join(out)

    def _by_chunks(self, text: str) -> bytes:
        first, *rest = text.split(" ")
        got = list(map(self.chunks.new.get, rest))
        if None in got:
            for k, ids in enumerate(got):
                if ids is None:
                    ids = self.chunks.get(rest[k])
                    if ids is None:
                        ids = self._chunk(" " + rest[k])
                        self.chunks.put(rest[k], ids)
                    got[k] = ids
        return self._chunk(first) + b"".join(got) if first else b"".join(got)

    def _parts(self, text: str) -> list[str]:
        """Parts of a long text, cut before a blank between two non-blanks."""
        out, at = [], 0
        while len(text) - at > LONGEST:
            cut = _SAFE_CUT.search(text, at + LONGEST)
            if not cut:
                break
            out.append(text[at : cut.start()])
            at = cut.start()
        return [*out, text[at:]]

    def _one(self, text: str) -> bytes:
        if not self.chunked or "  " in text or any(t in text for t in self.added):
            return self._library([text])[0]
        return self._by_chunks(text)

    def _many(self, texts: list[str]) -> list[bytes]:
        """Texts in groups; one that has no place to cut and is longer than the table's powers goes the other road."""
        raw = [t.encode("utf-8", "surrogatepass") for t in texts]
        out: list[bytes] = []
        at = 0
        while at < len(raw):
            to, size = at + 1, len(raw[at])
            while to < len(raw) and size + len(raw[to]) <= GROUP:
                size += len(raw[to])
                to += 1
            got = self.table.ids(raw[at:to]) if size <= 2 * GROUP else [None]
            out += [g if g is not None and not any(x in t for x in self.added) else self._one(t) for g, t in zip(got, texts[at:to], strict=True)]
            at = to
        return out

    def ids(self, texts: list[str]) -> list[bytes]:
        if not self.chunked:
            return self._library(texts)
        parts = [self._parts(t) if len(t) > LONGEST else [t] for t in texts]
        got = iter(self._many([p for ps in parts for p in ps]))
        return [b"".join(next(got) for _ in ps) if len(ps) > 1 else next(got) for ps in parts]


def encoder(path: str) -> Encoder:
    if path not in _loaded:
        _loaded.clear()
        _loaded[path] = Encoder(path)
    return _loaded[path]


def forget() -> None:
    """The worker goes on without an encoder; the next task that needs one loads it again."""
    _loaded.clear()


def public_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)
