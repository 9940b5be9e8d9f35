"""Vectorised word hashing over UTF-8 buffers: no Python work per word or per document."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from binlens.llm.common import KEPT, mix64

_BASE = 0x9E3779B97F4A7C15 | 1
_POWERS = np.ones(1, np.uint64)


def _forget_powers() -> None:
    global _POWERS
    _POWERS = np.ones(1, np.uint64)


KEPT.append(_forget_powers)


def _powers(n: int) -> np.ndarray:
    global _POWERS
    if len(_POWERS) < n:
        size = max(n, (1 << 17) + 64)
        with np.errstate(over="ignore"):
            grown = np.full(size, _BASE, np.uint64)
            grown[0] = 1
            _POWERS = np.cumprod(grown, dtype=np.uint64)
    return _POWERS


@dataclass(frozen=True)
class Alphabet:
    """Which bytes are part of a word, and how bytes are folded before hashing."""

    inside: np.ndarray
    fold: np.ndarray


def alphabet(separators: bytes) -> Alphabet:
    inside = np.ones(256, bool)
    inside[list(separators)] = False
    fold = np.arange(256, dtype=np.uint8)
    fold[65:91] += 32
    return Alphabet(inside, fold)


#: Words between ASCII white space.
SPACED = alphabet(b" \t\n\x0b\x0c\r")
#: Words of ASCII letters and digits and of everything beyond ASCII.
ALNUM = alphabet(bytes(i for i in range(128) if not chr(i).isalnum()))
#: Words of ASCII letters and of everything beyond ASCII.
ALPHA = alphabet(bytes(i for i in range(128) if not chr(i).isalpha()))


@dataclass
class Words:
    hashes: np.ndarray  # uint64, in text order
    start: np.ndarray  # byte position in the buffer
    end: np.ndarray
    first: np.ndarray  # rows + 1: words of row i are first[i]:first[i + 1]

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def rows(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.first) - 1), self.counts)


def spans(data: np.ndarray, offsets: np.ndarray, a: Alphabet) -> tuple[np.ndarray, np.ndarray]:
    """Byte spans of the words; a word never crosses a row."""
    n = len(data)
    if not n:
        return np.empty(0, np.int64), np.empty(0, np.int64)
    inside = a.inside[data]
    begins = inside.copy()
    begins[1:] &= ~inside[:-1]
    ends = inside.copy()
    ends[:-1] &= ~inside[1:]
    edge = offsets[1:-1]
    edge = edge[(edge > 0) & (edge < n)]
    begins[edge] |= inside[edge]
    ends[edge - 1] |= inside[edge - 1]
    return np.flatnonzero(begins), np.flatnonzero(ends) + 1


def span_hashes(data: np.ndarray, start: np.ndarray, end: np.ndarray, a: Alphabet, block: int = 1 << 17) -> np.ndarray:
    """Hash of each span: a polynomial over its folded bytes modulo 2^64, from one running sum, then mixed.

    Long buffers are cut into blocks between spans, so the running sum and the table of powers stay small.
    """
    out = np.empty(len(start), np.uint64)
    k = 0
    while k < len(start):
        lo = int(start[k])
        stop = max(k + 1, int(np.searchsorted(end, lo + block, "right")))
        hi = int(end[stop - 1]) if stop - 1 == k else int(end[k:stop].max())
        power = _powers(hi - lo + 1)
        with np.errstate(over="ignore"):
            run = np.zeros(hi - lo + 1, np.uint64)
            np.cumsum((a.fold[data[lo:hi]].astype(np.uint64) + np.uint64(1)) * power[: hi - lo], out=run[1:])
            s, e = start[k:stop] - lo, end[k:stop] - lo
            out[k:stop] = (run[e] - run[s]) * power[(hi - lo) - s]
            # brought to one scale: the factor BASE^(hi - lo) is divided out by its inverse
            out[k:stop] *= np.uint64(pow(_BASE, -(hi - lo), 1 << 64))
            out[k:stop] = mix64(out[k:stop] + (e - s).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))
        k = stop
    return out


def words(data: np.ndarray, offsets: np.ndarray, a: Alphabet) -> Words:
    start, end = spans(data, offsets, a)
    return Words(span_hashes(data, start, end, a), start, end, np.searchsorted(start, offsets, "left"))


def hash_of(word: str, a: Alphabet = SPACED) -> int:
    """Hash of one word, as ``words`` gives it."""
    raw = np.frombuffer(word.encode(), np.uint8)
    return int(span_hashes(raw, np.zeros(1, np.int64), np.array([len(raw)]), a)[0])


def windows(hashes: np.ndarray, first: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash of each run of ``size`` consecutive words of one row, and the position of its first word."""
    n = len(hashes)
    if n < size:
        return np.empty(0, np.uint64), np.empty(0, np.int64)
    ok = np.ones(n - size + 1, bool)
    for back in range(1, size):  # a window that begins fewer than `size` words before a row's end
        at = first[1:] - back
        at = at[(at >= 0) & (at < len(ok))]
        ok[at] = False
    with np.errstate(over="ignore"):
        total = np.zeros(n - size + 1, np.uint64)
        for k in range(size):
            total *= np.uint64(0xC2B2AE3D27D4EB4F)
            total += hashes[k : n - size + 1 + k]
    at = np.flatnonzero(ok)
    return mix64(total[at]), at
