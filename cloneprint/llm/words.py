"""Words and word hashes of UTF-8 text, in numpy over bytes.

Words are runs of bytes other than the six ASCII blanks; A-Z count as a-z.
A word's hash is a polynomial in its bytes modulo 2**64, mixed.
"""

from __future__ import annotations

import numpy as np

PIECE = 1 << 20  # bytes hashed at a time; longer texts are cut at blanks
SHINGLE = 5
_rng = np.random.default_rng(20240607)
_BLANK = np.zeros(256, dtype=bool)
_BLANK[[9, 10, 11, 12, 13, 32]] = True
#: also every ASCII mark: words of letters, digits and non-ASCII characters only
MARKS = np.ones(256, dtype=bool)
MARKS[48:58] = MARKS[65:91] = MARKS[97:123] = MARKS[128:] = False
_VALUE = _rng.integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_VALUE[65:91] = _VALUE[97:123]
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)
_MIX = _rng.integers(1, 1 << 63, 64, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    size = 1 << max(12, int(n).bit_length())
    if size not in _powers:
        _powers.clear()
        with np.errstate(over="ignore"):
            up, down = np.full(size, _BASE, np.uint64), np.full(size, _INVERSE, np.uint64)
            up[0] = down[0] = 1
            _powers[size] = np.cumprod(up, dtype=np.uint64), np.cumprod(down, dtype=np.uint64)
    return _powers[size]


def mix(x: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


def _piece_words(raw: np.ndarray, gap: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    blank = gap[raw]
    edge = np.flatnonzero(blank[1:] != blank[:-1]) + 1
    edge = np.concatenate(([0] * (not blank[0]), edge, [len(raw)] * (not blank[-1]))).astype(np.int64)
    start, end = edge[0::2], edge[1::2]
    up, down = _power_tables(len(raw) + 1)
    with np.errstate(over="ignore"):
        total = np.zeros(len(raw) + 1, np.uint64)
        np.cumsum(_VALUE[raw] * up[: len(raw)], out=total[1:])
        hashed = (total[end] - total[start]) * down[start]
    return mix(hashed), start, end


def word_hashes(text: bytes, gap: np.ndarray = _BLANK) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hash, start and end byte of each word."""
    if not text:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    raw, parts, at = np.frombuffer(text, np.uint8), [], 0
    while at < len(raw):
        to = min(len(raw), at + PIECE)
        while to < len(raw):  # a word never straddles two pieces
            gaps = np.flatnonzero(gap[raw[at:to]])
            if len(gaps):
                to = at + int(gaps[-1]) + 1
                break
            to = min(len(raw), to + PIECE)
        h, s, e = _piece_words(raw[at:to], gap)
        parts.append((h, s + at, e + at))
        at = to
    if len(parts) == 1:
        return parts[0]
    return tuple(np.concatenate(x) for x in zip(*parts, strict=True))  # type: ignore[return-value]


def ngrams(words: np.ndarray, n: int) -> np.ndarray:
    """Hash of each run of n word hashes; empty if there are fewer."""
    if len(words) < n:
        return np.zeros(0, np.uint64)
    with np.errstate(over="ignore"):
        out = words[: len(words) - n + 1] * _MIX[0]
        for k in range(1, n):
            out += words[k : len(words) - n + 1 + k] * _MIX[k]
    return mix(out)


def shingle_set(text: bytes | None, n: int = SHINGLE) -> np.ndarray:
    """Sorted distinct n-word shingles; the whole sequence if it is shorter; empty without words."""
    words = word_hashes(text or b"")[0]
    if 0 < len(words) < n:
        with np.errstate(over="ignore"):
            short = words * _MIX[8 : 8 + len(words)]
            return mix(np.array([short.sum(dtype=np.uint64) + _MIX[16 + len(words)]], np.uint64))
    return np.unique(ngrams(words, n))


def text_bytes(column) -> list[bytes | None]:
    """A string column's values as bytes, without decoding them."""
    import pyarrow as pa

    return column.cast(pa.binary() if not pa.types.is_large_string(column.type) else pa.large_binary()).to_pylist()
