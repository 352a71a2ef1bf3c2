"""Vectorised byte kernels over Arrow string columns.

Texts stay in the Arrow buffer: a column is seen as one byte array plus offsets, every
n-gram or word of every row is hashed by whole-array operations, and a row's share is
read off by its offsets. No Python string is made.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Bytes of text worked on at a time; longer single rows are taken alone, whole.
CHUNK_BYTES = 1 << 20
_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_BASE_INV = np.uint64(pow(int(_BASE), -1, 1 << 64))


def chunks(batch: pa.RecordBatch, column: str, limit: int = CHUNK_BYTES) -> Iterator[pa.RecordBatch]:
    """Zero-copy slices of `batch` whose `column` holds about `limit` bytes each."""
    n = batch.num_rows
    if not n:
        return
    _, off = view(batch.column(batch.schema.get_field_index(column)))
    at = 0
    while at < n:
        to = max(at + 1, int(np.searchsorted(off, off[at] + limit, "right")) - 1)
        yield batch.slice(at, to - at)
        at = to


def view(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; a null has no bytes."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    if not pa.types.is_large_string(col.type):
        col = col.cast(pa.large_string())
    if col.null_count:
        col = col.fill_null("")
    n = len(col)
    if not n or col.buffers()[1] is None:
        return np.zeros(0, np.uint8), np.zeros(n + 1, np.int64)
    off = np.frombuffer(col.buffers()[1], np.int64, n + 1, col.offset * 8)
    lo, hi = int(off[0]), int(off[-1])
    buf = np.frombuffer(col.buffers()[2], np.uint8, hi - lo, lo) if hi > lo else np.zeros(0, np.uint8)
    return buf, off - lo


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads every bit of a uint64 over the word."""
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x ^= x >> np.uint64(33)
    x *= np.uint64(0xC4CEB9FE1A85EC53)
    x ^= x >> np.uint64(33)
    return x


def byte_grams(buf: np.ndarray, n: int) -> np.ndarray:
    """Value of the n bytes that begin at each position (n up to 4), as uint32; the last n-1 positions are left out."""
    m = len(buf) - n + 1
    if m <= 0:
        return np.zeros(0, np.uint32)
    g = buf[:m].astype(np.uint32)
    for k in range(1, n):
        g <<= np.uint32(8)
        g |= buf[k : k + m]
    return g


def bucket(gram: np.ndarray, salt: int, bits: int) -> np.ndarray:
    """Multiply-shift bucket of uint32 values: `bits` bits."""
    m = np.uint32((0x9E3779B1 * (2 * salt + 1) ^ 0x85EBCA6B * salt) & 0xFFFFFFFF | 1)
    return (gram * m ^ (gram >> np.uint32(15)) * np.uint32(0x2C1B3C6D)) >> np.uint32(32 - bits)


def row_sums(values: np.ndarray, off: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Per row, the sum of `values` over the n-gram positions inside that row, and their number."""
    total = np.zeros(len(values) + 1)
    np.cumsum(values, out=total[1:])
    hi = np.maximum(off[1:] - n + 1, off[:-1])
    return total[np.minimum(hi, len(values))] - total[np.minimum(off[:-1], len(values))], hi - off[:-1]


_powers: dict[str, np.ndarray] = {}


def _pow(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers.get("r", ())) < n:
        size = max(n, CHUNK_BYTES + (CHUNK_BYTES >> 2))
        for k, base in (("r", _BASE), ("i", _BASE_INV)):
            p = np.full(size, base, np.uint64)
            p[0] = 1
            _powers[k] = np.cumprod(p, dtype=np.uint64)
    return _powers["r"], _powers["i"]


def words(buf: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(hashes of the white-space separated words, offsets of each row's words)."""
    n = len(buf)
    if not n:
        return np.zeros(0, np.uint64), np.zeros(len(off), np.int64)
    solid = np.zeros(n + 2, bool)
    solid[1:-1] = buf > 32
    edge = np.zeros(n + 1, bool)
    edge[off] = True
    start = np.flatnonzero(solid[1:-1] & (~solid[:-2] | edge[:-1]))
    end = np.flatnonzero(solid[1:-1] & (~solid[2:] | edge[1:])) + 1
    r, inv = _pow(n)
    total = np.zeros(n + 1, np.uint64)
    np.cumsum((buf.astype(np.uint64) + np.uint64(1)) * r[:n], out=total[1:])
    h = mix((total[end] - total[start]) * inv[start])
    return h, np.searchsorted(start, off)


def lowered(col: pa.Array) -> pa.Array:
    import pyarrow.compute as pc

    return pc.utf8_lower(col)


def shingles(h: np.ndarray, off: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of each row's runs of k words (a shorter row is one run), not yet distinct, with their offsets."""
    n = np.diff(off)
    count = np.where(n >= k, n - k + 1, np.minimum(n, 1))
    out_off = np.concatenate([[0], np.cumsum(count)])
    if not len(h):
        return np.zeros(0, np.uint64), out_off
    m = len(h)
    acc = h.copy()
    for j in range(1, k):
        acc[: m - j] = mix(acc[: m - j] * np.uint64(3) + h[j:])
    pos = np.repeat(off[:-1] - out_off[:-1], count) + np.arange(out_off[-1])
    out = acc[pos]
    for i in np.flatnonzero((n > 0) & (n < k)):
        v = h[off[i] : off[i] + 1]
        for at in range(off[i] + 1, off[i + 1]):
            v = mix(v * np.uint64(3) + h[at : at + 1])
        out[out_off[i]] = v[0]
    return out, out_off
