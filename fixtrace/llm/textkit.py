"""Vectorised word, shingle and text-statistics kernels shared by the Arrow stages (numpy, no Spark).

A text is handled as UTF-8 bytes.  Words are maximal runs of bytes outside ``[\\x20\\x09-\\x0D]``; as UTF-8 never
uses those bytes inside a longer code point, byte runs and code-point runs agree.
"""

from __future__ import annotations

import numpy as np

U64 = np.uint64
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, 9, 10, 11, 12, 13]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_STEP = 0x9E3779B97F4A7C15 | 1
_STEP_INVERSE = pow(_STEP, -1, 1 << 64)
_CHUNK = 1 << 20

_powers = np.ones(1, U64)
_inverses = np.ones(1, U64)


def _grow(n: int) -> None:
    """Make the power tables at least ``n`` long (they stay at one chunk unless one word is longer)."""
    global _powers, _inverses
    if len(_powers) < n:
        size = max(n, 1 << 12)
        one = np.full(size, _STEP, U64)
        one[0] = 1
        other = np.full(size, _STEP_INVERSE, U64)
        other[0] = 1
        with np.errstate(over="ignore"):
            _powers, _inverses = np.cumprod(one, dtype=U64), np.cumprod(other, dtype=U64)


def mix(x: np.ndarray, salt: int = 0) -> np.ndarray:
    """A 64-bit finaliser: a bijection that spreads every input bit."""
    with np.errstate(over="ignore"):
        x = x + U64((0x632BE59BD9B4E019 * (salt + 1)) & 0xFFFFFFFFFFFFFFFF)
        x = (x ^ (x >> U64(30))) * U64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> U64(27))) * U64(0x94D049BB133111EB)
        return x ^ (x >> U64(31))


def spans(a: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Start and end offsets of the words in a byte array."""
    edge = np.flatnonzero(np.diff(_SPACE[a].astype(np.int8), prepend=np.int8(1), append=np.int8(1)))
    return edge[0::2], edge[1::2]


def _hash_chunk(a: np.ndarray) -> np.ndarray:
    begin, end = spans(a)
    if not len(begin):
        return np.empty(0, U64)
    _grow(len(a) + 1)
    with np.errstate(over="ignore"):
        total = np.zeros(len(a) + 1, U64)
        np.cumsum((a.astype(U64) + U64(1)) * _powers[: len(a)], out=total[1:])
        return mix((total[end] - total[begin]) * _inverses[begin] + (end - begin).astype(U64))


def word_hashes(text: str | bytes | None, lower: bool = False) -> np.ndarray:
    """One 64-bit hash per word, in order; ``lower`` folds A-Z only.  A null text has no words."""
    if not text:
        return np.empty(0, U64)
    a = np.frombuffer(text.encode("utf-8", "surrogatepass") if isinstance(text, str) else text, np.uint8)
    if lower:
        a = _LOWER[a]
    if len(a) <= _CHUNK:
        return _hash_chunk(a)
    parts, at = [], 0
    while at < len(a):
        to = min(at + _CHUNK, len(a))
        while to < len(a) and not _SPACE[a[to]]:  # a chunk ends before white space, so no word is cut
            to += 1
        parts.append(_hash_chunk(a[at:to]))
        at = to
    return np.concatenate(parts)


def windows(words: np.ndarray, width: int) -> np.ndarray:
    """Hash of each run of ``width`` words, in order."""
    n = len(words) - width + 1
    if n <= 0:
        return np.empty(0, U64)
    with np.errstate(over="ignore"):
        h = words[:n].copy()
        for k in range(1, width):
            h = h * U64(0xD6E8FEB86659FD93) + words[k : k + n]
    return mix(h, width)


def shingles(text: str | bytes | None, width: int) -> np.ndarray:
    """The sorted distinct shingles; fewer words than ``width`` make one shingle, no words none."""
    words = word_hashes(text, lower=True)
    if not len(words):
        return np.empty(0, U64)
    return np.unique(windows(words, min(width, len(words))))
