"""Vectorised word hashing on the UTF-8 buffers of Arrow string arrays.

A word is a longest run of ASCII letters, digits and non-ASCII bytes; ASCII
capitals count as small letters.  All words of a block are hashed at once: with
``C`` the running sum of ``code[byte] * R**i`` (mod 2**64) the hash of bytes
``s..e`` is ``(C[e] - C[s]) * R**-s``, so no Python string is ever built.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

U = np.uint64
_R = 0x9E3779B97F4A7C15
_R_INVERSE = pow(_R, -1, 2**64)
#: Bytes hashed in one go; bounds the working memory whatever the batch holds.
BLOCK = 1 << 20


def _codes() -> np.ndarray:
    codes = np.random.default_rng(20011).integers(1, 2**63, 256, dtype=np.uint64)
    codes[65:91] = codes[97:123]
    return codes


_CODE = _codes()
_WORD = np.zeros(256, dtype=bool)
_WORD[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = True
_STOP = np.zeros(256, dtype=bool)
_STOP[[ord(c) for c in ".!?\n"]] = True
_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    size = BLOCK
    while size < n:
        size *= 2
    if size not in _powers:
        up, down = np.full(size, _R, dtype=np.uint64), np.full(size, _R_INVERSE, dtype=np.uint64)
        up[0] = down[0] = 1
        pair = np.cumprod(up), np.cumprod(down)
        if size > BLOCK:  # an unusually long word: do not keep its tables
            return pair
        _powers[size] = pair
    return _powers[size]


def scramble(h: np.ndarray, salt: int = 0) -> np.ndarray:
    """A bijective 64-bit finaliser; ``salt`` selects one of many."""
    h = h + U((salt * _R) % 2**64)
    h = (h ^ (h >> U(30))) * U(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> U(27))) * U(0x94D049BB133111EB)
    return h ^ (h >> U(31))


@dataclass
class Words:
    """Word hashes with byte positions in ``data``, and the words of each text:
    text ``i`` owns ``first[i]:first[i + 1]``."""

    data: np.ndarray
    offsets: np.ndarray
    hash: np.ndarray
    start: np.ndarray
    end: np.ndarray
    first: np.ndarray
    #: For each length asked for, the hashes of the words' first bytes; 0 for shorter words.
    prefix: list[np.ndarray]


def _hash_block(data: np.ndarray, breaks: np.ndarray, lengths: tuple[int, ...]) -> tuple[np.ndarray, ...]:
    n = len(data)
    word = np.zeros(n + 2, dtype=bool)
    word[1:-1] = _WORD[data]
    edge = np.zeros(n + 1, dtype=bool)
    edge[breaks] = True
    start = np.flatnonzero(word[1:] & (~word[:-1] | edge))
    end = np.flatnonzero(word[:-1] & (~word[1:] | edge))
    up, down = _power_tables(n)
    total = np.empty(n + 1, dtype=np.uint64)
    total[0] = 0
    np.cumsum(_CODE[data] * up[:n], out=total[1:])
    unshift = down[np.minimum(start, max(n - 1, 0))]
    beginnings = []
    for k in lengths:
        h = scramble((total[np.minimum(start + k, n)] - total[start]) * unshift, k)
        h[end - start < k] = 0
        beginnings.append(h)
    return scramble((total[end] - total[start]) * unshift), start, end, *beginnings


def word_hashes(data: np.ndarray, offsets: np.ndarray, prefixes: tuple[int, ...] = ()) -> Words:
    """``offsets`` (length texts + 1) cut ``data`` into texts; starts at 0."""
    parts, at, n = [], 0, len(data)
    while at < n:
        to = min(n, at + BLOCK)
        while to < n and _WORD[data[to - 1]] and _WORD[data[to]]:  # to the end of the word
            step = _WORD[data[to : to + 4096]]
            to += len(step) if step.all() else int(step.argmin())
        inside = offsets[(offsets >= at) & (offsets <= to)] - at
        h, s, e, *beginnings = _hash_block(data[at:to], inside, prefixes)
        parts.append((h, s + at, e + at, *beginnings))
        at = to
    if not parts:
        parts = [(np.empty(0, np.uint64), np.empty(0, np.int64), np.empty(0, np.int64), *[np.empty(0, np.uint64) for _ in prefixes])]
    h, s, e, *beginnings = (np.concatenate(x) for x in zip(*parts, strict=True))
    return Words(data, offsets, h, s, e, np.searchsorted(s, offsets), beginnings)


def sentence_numbers(w: Words) -> np.ndarray:
    """For each word, how many sentence ends lie before it in ``data``."""
    ends = np.flatnonzero(_STOP[w.data])
    return np.searchsorted(ends, w.start)


def buffers(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes and offsets from 0; a null counts as an empty text."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    if texts.null_count:
        texts = texts.fill_null("")
    texts = texts.cast(pa.large_string())
    raw = texts.buffers()
    offsets = np.frombuffer(raw[1], dtype=np.int64)[texts.offset : texts.offset + len(texts) + 1] if len(texts) else np.zeros(1, np.int64)
    data = np.frombuffer(raw[2], dtype=np.uint8)[offsets[0] : offsets[-1]] if raw[2] is not None and len(texts) else np.empty(0, np.uint8)
    return data, offsets - offsets[0]


def pieces(texts: pa.Array, limit: int = BLOCK) -> Iterator[pa.Array]:
    """Slices of about ``limit`` bytes at most; a longer text comes alone."""
    _, offsets = buffers(texts)
    at = 0
    while at < len(texts):
        to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + limit, side="right")) - 1)
        yield texts[at:to]
        at = to


try:
    _trim = ctypes.CDLL(None).malloc_trim
except AttributeError:  # not glibc
    _trim = None


def give_back() -> None:
    """Memory that is free in this process goes back to the machine: a worker waits for its next
    task without what the last one took."""
    pa.default_memory_pool().release_unused()
    if _trim:
        _trim(0)
