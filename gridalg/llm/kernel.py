"""Byte-level text kernels on numpy, shared by the operators that work on words.

A batch of texts is taken as the contiguous UTF-8 buffer that Arrow holds already. Words, their 64-bit
hashes and hashes of word windows come from a few vectorised passes, without a Python object per word.
Every word class used here contains all bytes from 0x80 up or none that split a character, so working on
bytes equals working on characters.
"""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator
from functools import wraps

import numpy as np
import pyarrow as pa

U64 = np.uint64
_MULT = 0x9E3779B97F4A7C15 | 1
_INV = pow(_MULT, -1, 1 << 64)
_WINDOW = U64(0xD6E8FEB86659FD93)
PIECE = 1 << 18

_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_VALUE = np.random.default_rng(20240117).integers(1, 1 << 63, 256, dtype=np.uint64) | U64(1)


def hand_back() -> None:
    """Memory that was freed goes back to the system, where the C library can do that."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def tidy(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]):
    """run, with the memory that it freed handed back in the end: a worker waits for its next task with what it needs."""

    @wraps(run)
    def tidied(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from run(batches)
        hand_back()

    return tidied


def kept(batch: pa.RecordBatch, mask: np.ndarray, rows: int = 1000) -> Iterator[pa.RecordBatch]:
    """The rows of a batch where the mask is set, in small batches."""
    for lo in range(0, batch.num_rows, rows):
        yield batch.slice(lo, rows).filter(pa.array(mask[lo : lo + rows]))


def byte_class(pattern: str) -> np.ndarray:
    """Bytes of single-byte characters that the one-character pattern takes, and all bytes of longer ones."""
    import re

    return np.array([i > 127 or re.match(pattern, chr(i)) is not None for i in range(256)])


#: The class is meant for lower-cased text, so that of a capital is that of its small letter.
ALNUM = byte_class(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]")[_LOWER]
NONSPACE = byte_class(r"[^\x20\x09-\x0D]")

_powers: dict[str, np.ndarray] = {}


def _power(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers.get("p", ())) < n:
        size = max(n, PIECE + 4096)
        with np.errstate(over="ignore"):
            _powers["p"] = np.cumprod(np.concatenate([[U64(1)], np.full(size, U64(_MULT))]), dtype=U64)
            _powers["i"] = np.cumprod(np.concatenate([[U64(1)], np.full(size, U64(_INV))]), dtype=U64)
    return _powers["p"], _powers["i"]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection that spreads all 64 bits."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> U64(30))) * U64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> U64(27))) * U64(0x94D049BB133111EB)
        return x ^ (x >> U64(31))


def buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a string column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    if column.type not in (pa.string(), pa.binary(), pa.large_string(), pa.large_binary()):
        column = column.cast(pa.large_string())
    _, offsets, data = column.buffers()
    wide = column.type in (pa.large_string(), pa.large_binary())
    if offsets is None or not offsets.size:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    at = np.frombuffer(offsets, dtype=np.int64 if wide else np.int32, count=len(column) + 1 + column.offset)[column.offset :].astype(np.int64)
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[at[0] : at[-1]], at - at[0]


def pieces(offsets: np.ndarray, limit: int = PIECE) -> Iterator[tuple[int, int]]:
    """Runs of whole rows of about limit bytes; a longer row stands alone."""
    first, n = 0, len(offsets) - 1
    while first < n:
        last = int(np.searchsorted(offsets, offsets[first] + limit, side="right")) - 1
        last = min(n, max(last, first + 1))
        yield first, last
        first = last


def _hash_piece(raw: np.ndarray, breaks: np.ndarray, word: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    inside = word[raw]
    cut = np.zeros(len(raw) + 1, bool)
    cut[breaks] = True
    start = inside.copy()
    start[1:] &= ~inside[:-1] | cut[1:-1]
    end = inside.copy()
    end[:-1] &= ~inside[1:] | cut[1:-1]
    s, e = np.flatnonzero(start), np.flatnonzero(end) + 1
    p, i = _power(len(raw) + 1)
    with np.errstate(over="ignore"):
        total = np.zeros(len(raw) + 1, U64)
        np.cumsum(_VALUE[_LOWER[raw]] * p[: len(raw)], out=total[1:])
        h = mix((total[e] - total[s]) * i[s] + (e - s).astype(U64))
    return s, e, h


def words(raw: np.ndarray, offsets: np.ndarray, word: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Start, end and hash of each lower-cased word, and the index of the first word of each row (one more at the end).

    Memory is bounded by PIECE and the words of the given rows: long rows are cut between words.
    """
    out, at, n = [], 0, len(raw)
    while at < n:
        to = min(n, at + PIECE)
        if to < n:
            gap = np.flatnonzero(~word[raw[at:to]])
            if len(gap):
                to = at + int(gap[-1]) + 1
            else:  # one word longer than a piece
                while to < n and word[raw[to]]:
                    to += 1
        lo, hi = np.searchsorted(offsets, [at, to])
        s, e, h = _hash_piece(raw[at:to], offsets[lo : np.searchsorted(offsets, to, side="right")] - at, word)
        out.append((s + at, e + at, h))
        at = to
    if not out:
        z = np.zeros(0, np.int64)
        return z, z, np.zeros(0, U64), np.zeros(len(offsets), np.int64)
    s, e, h = (np.concatenate(x) for x in zip(*out, strict=True))
    return s, e, h, np.searchsorted(s, offsets)


def windows(h: np.ndarray, size: int) -> np.ndarray:
    """A hash of each run of size words, also over row ends: callers leave those out."""
    n = len(h) - size + 1
    if n <= 0:
        return np.zeros(0, U64)
    with np.errstate(over="ignore"):
        acc = np.full(n, U64(size), U64)
        for k in range(size):
            acc = acc * _WINDOW + h[k : k + n]
        return mix(acc)


def row_windows(h: np.ndarray, first: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Window hashes that stay inside their row, and the index of each one's first word."""
    w = windows(h, size)
    if not len(w):
        return w, np.zeros(0, np.int64)
    ok = np.ones(len(w), bool)
    for k in range(1, size):  # a window may not start in the last size-1 words of a row
        at = first[1:] - k
        at = at[(at >= 0) & (at < len(w))]
        ok[at] = False
    at = np.flatnonzero(ok)
    return w[at], at
