"""Vectorised word scanning over Arrow string columns (NumPy, whole texts).

A column is viewed as one byte buffer plus offsets, so a batch of documents is
tokenised and hashed with a few array passes instead of a Python loop per word.
Words never run across a document boundary.  Null texts count as empty.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U64 = np.uint64
_BASE = U64(0x9E3779B97F4A7C15 | 1)
_INV = U64(pow(int(_BASE), -1, 1 << 64))
_POW: list[np.ndarray] = [np.ones(1, U64), np.ones(1, U64)]


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """base**i and base**-i modulo 2**64 for i < n, kept between calls."""
    if len(_POW[0]) < n:
        size = max(n, 1 << 20)
        for k, b in enumerate((_BASE, _INV)):
            p = np.full(size, b, U64)
            p[0] = 1
            _POW[k] = np.cumprod(p, dtype=U64)
    return _POW[0], _POW[1]


def mix(x: np.ndarray) -> np.ndarray:
    """64-bit finaliser (murmur style) on an uint64 array."""
    x = x ^ (x >> U64(33))
    x = x * U64(0xFF51AFD7ED558CCD)
    x ^= x >> U64(33)
    x *= U64(0xC4CEB9FE1A85EC53)
    x ^= x >> U64(33)
    return x


def text_slices(batch: pa.RecordBatch, column: str, max_bytes: int = 2 << 20) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, last row, bytes, offsets) for runs of rows of about max_bytes, always whole texts."""
    arr = batch.column(batch.schema.get_field_index(column))
    arr = arr.cast(pa.large_binary()) if not pa.types.is_large_binary(arr.type) else arr
    if arr.null_count:
        arr = arr.fill_null(b"")
    n = len(arr)
    if not n:
        return
    off = np.frombuffer(arr.buffers()[1], np.int64, n + 1, arr.offset * 8)
    data = np.frombuffer(arr.buffers()[2], np.uint8) if arr.buffers()[2] is not None and off[-1] else np.zeros(0, np.uint8)
    lo = 0
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(off, off[lo] + max_bytes, side="right")) - 1)
        hi = min(hi, n)
        yield lo, hi, data[off[lo] : off[hi]], off[lo : hi + 1] - off[lo]
        lo = hi


def byte_table(separators: bytes, lower: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """(is-word flag, lower-cased byte) by byte value; only A-Z are lower-cased."""
    flag = np.ones(256, bool)
    flag[list(separators)] = False
    low = np.arange(256, dtype=np.uint8)
    if lower:
        low[65:91] += 32
    return flag, low


#: Separators: everything ASCII but digits and letters (after lower-casing).
ALNUM_WORDS = byte_table(bytes(b for b in range(128) if not (48 <= b < 58 or 97 <= b < 123 or 65 <= b < 91)))
#: Separators: space and the control characters 9 to 13.
SPACE_WORDS = byte_table(bytes([32, *range(9, 14)]))


def words(buf: np.ndarray, off: np.ndarray, table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(starts, ends, document index) of all words."""
    if not len(buf):
        z = np.zeros(0, np.int64)
        return z, z, z
    w = table[0][buf]
    first = w.copy()
    first[1:] &= ~w[:-1]
    last = w.copy()
    last[:-1] &= ~w[1:]
    edge = off[1:-1]
    edge = edge[(edge > 0) & (edge < len(buf))]
    first[edge] = w[edge]
    last[edge - 1] = w[edge - 1]
    starts, ends = np.flatnonzero(first), np.flatnonzero(last) + 1
    return starts, ends, np.searchsorted(off[1:], starts, side="right")


def word_hashes(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray, table) -> np.ndarray:
    """A 64-bit hash of each (lower-cased) word."""
    if not len(starts):
        return np.zeros(0, U64)
    p, q = _powers(len(buf) + 1)
    total = np.zeros(len(buf) + 1, U64)
    np.cumsum((table[1][buf].astype(U64) + U64(1)) * p[: len(buf)], out=total[1:], dtype=U64)
    h = (total[ends] - total[starts]) * q[starts]
    return mix(h + (ends - starts).astype(U64) * U64(0xD6E8FEB86659FD93))


def ngram_hashes(h: np.ndarray, w: int) -> np.ndarray:
    """Hash of each run of w consecutive word hashes (len(h) - w + 1 of them)."""
    if len(h) < w:
        return np.zeros(0, U64)
    n = len(h) - w + 1
    s = np.zeros(n, U64)
    for i in range(w):
        s = s * U64(0x2545F4914F6CDD1D) + h[i : i + n]
    return mix(s + U64(w))


def shingle_sets(buf: np.ndarray, off: np.ndarray, w: int, table=SPACE_WORDS) -> Iterator[np.ndarray]:
    """The sorted distinct shingle hashes of each document in turn.

    Fewer than w words: the whole word sequence is the one shingle.  No words: the empty set."""
    starts, ends, _ = words(buf, off, table)
    h = word_hashes(buf, starts, ends, table)
    s = ngram_hashes(h, w)
    at = np.searchsorted(starts, off)
    for a, b in zip(at[:-1].tolist(), at[1:].tolist()):
        if b - a >= w:
            x = np.sort(s[a : b - w + 1])
            yield x[np.concatenate(([True], x[1:] != x[:-1]))]
        elif b > a:
            yield ngram_hashes(h[a:b], b - a)
        else:
            yield s[:0]
