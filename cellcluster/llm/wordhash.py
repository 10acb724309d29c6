"""Word and shingle fingerprints of raw UTF-8, vectorised with NumPy.

Words are runs of bytes that a 256-entry table does not map to a blank, so one
``bytes.translate`` lower-cases A-Z and blanks separators without decoding.
Bytes above 0x7F belong to multi-byte characters and always stay in a word.
"""

from __future__ import annotations

import numpy as np

WHITE = bytes([0x20, *range(0x09, 0x0E)])
_BLANK = 0x20
_M64 = (1 << 64) - 1


def _table(is_separator) -> bytes:
    out = bytearray(range(256))
    for b in range(256):
        if is_separator(b):
            out[b] = _BLANK
        elif 0x41 <= b <= 0x5A:
            out[b] = b + 0x20
    return bytes(out)


#: Words are separated by white space only.
SPACED = _table(lambda b: b in WHITE)
#: Words are runs of digits, ASCII letters and non-ASCII characters.
ALNUM = _table(lambda b: b <= 0x2F or 0x3A <= b <= 0x40 or 0x5B <= b <= 0x60 or 0x7B <= b <= 0x7F)

_rng = np.random.Generator(np.random.PCG64(0x5EED))
_BYTE = _rng.integers(1, 2**63, 256, dtype=np.uint64) | np.uint64(1)
_P = 0x9E3779B97F4A7C15 | 1
_P_INV = pow(_P, -1, 1 << 64)
_STEP = np.array([pow(0xD6E8FEB86659FD93, k, 1 << 64) for k in range(64)], dtype=np.uint64)


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, dtype=np.uint64)
    if n:
        out[0] = 1
    with np.errstate(over="ignore"):
        return np.cumprod(out, dtype=np.uint64)


_cache: dict[str, np.ndarray] = {"p": _powers(_P, 1 << 17), "i": _powers(_P_INV, 1 << 17)}


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


#: Bytes of text that are hashed at a time; the tables of powers grow beyond it for a longer word only.
STRETCH = 1 << 16


def word_hashes(raw: bytes, table: bytes = SPACED) -> np.ndarray:
    """A 64-bit hash for each word of the text, in order; the whole text counts, in stretches that end at a blank."""
    data = np.frombuffer(raw.translate(table), dtype=np.uint8)
    if len(data) <= STRETCH:
        return _hashes(data)
    blank, out, a = np.flatnonzero(data == _BLANK), [], 0
    while a < len(data):
        k = int(np.searchsorted(blank, a + STRETCH))
        b = int(blank[k]) if k < len(blank) else len(data)
        out.append(_hashes(data[a:b]))
        a = b
    return np.concatenate(out)


def _hashes(data: np.ndarray) -> np.ndarray:
    if not len(data):
        return np.empty(0, dtype=np.uint64)
    p, i = _cache["p"], _cache["i"]
    if len(data) > len(p):
        p, i = _powers(_P, len(data)), _powers(_P_INV, len(data))  # not kept
    inside = np.empty(len(data) + 2, dtype=np.int8)
    inside[0] = inside[-1] = 0
    inside[1:-1] = data != _BLANK
    edge = np.diff(inside)
    start, end = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    with np.errstate(over="ignore"):
        total = np.zeros(len(data) + 1, dtype=np.uint64)
        np.cumsum(_BYTE[data] * p[: len(data)], out=total[1:])
        return mix((total[end] - total[start]) * i[start] + (end - start).astype(np.uint64))


def shingles(words: np.ndarray, width: int = 5) -> np.ndarray:
    """Sorted distinct fingerprints of ``width`` words in a row; fewer words make one shingle."""
    if not len(words):
        return words
    w = min(width, len(words))
    n = len(words) - w + 1
    with np.errstate(over="ignore"):
        out = np.full(n, w, dtype=np.uint64)
        for k in range(w):
            out += words[k : k + n] * _STEP[k + 1]
    return np.unique(mix(out))
