"""NumPy kernels over UTF-8 bytes that the Python-side operators share.

All of them work on blocks of whole rows of bounded size, so memory depends on
the block (or the longest single text), never on the Arrow batch.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

BLOCK = 1 << 19
_M64 = (1 << 64) - 1
_B = 0x9E3779B97F4A7C15
_B_INV = pow(_B, -1, 1 << 64)
_powers: dict[str, np.ndarray] = {}


def mix(h: np.ndarray) -> np.ndarray:
    """Finaliser that spreads every input bit over the 64 output bits."""
    h = h ^ (h >> np.uint64(32))
    h *= np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xA3B195354A39B70D)
    h ^= h >> np.uint64(32)
    return h


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """First n powers modulo 2^64 of the hash base and of its inverse."""
    if "b" not in _powers or len(_powers["b"]) < n:
        size = max(n, BLOCK + 1)
        for key, base in (("b", _B), ("i", _B_INV)):
            a = np.full(size, base, dtype=np.uint64)
            a[0] = 1
            _powers[key] = np.multiply.accumulate(a)
    return _powers["b"][:n], _powers["i"][:n]


def byte_table(fold: bool) -> np.ndarray:
    """A random 64-bit value for each byte; with fold, A-Z hash as a-z."""
    t = mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(_B))
    if fold:
        t[65:91] = t[97:123]
    return t


_PLAIN, _FOLDED = byte_table(False), byte_table(True)


def separators(extra: bytes = b"") -> np.ndarray:
    """True for space, tab to carriage return, and the extra bytes."""
    sep = np.zeros(256, dtype=bool)
    sep[32] = True
    sep[9:14] = True
    sep[list(extra)] = True
    return sep


SPACES = separators()


def utf8(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and row offsets of a string or binary column; null is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = pc.fill_null(column, b"" if pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type) else "")
    large = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, off, data = column.buffers()
    kind = np.int64 if large else np.int32
    if len(column) == 0 or off is None:
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    offsets = np.frombuffer(off, dtype=kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def blocks(offsets: np.ndarray, limit: int = BLOCK):
    """Row ranges of about ``limit`` bytes each, one row at least."""
    lo, n = 0, len(offsets) - 1
    while lo < n:
        hi = int(np.searchsorted(offsets, offsets[lo] + limit, side="right")) - 1
        hi = min(max(hi, lo + 1), n)
        yield lo, hi
        lo = hi


def words(data: np.ndarray, offsets: np.ndarray, sep: np.ndarray = SPACES) -> tuple[np.ndarray, np.ndarray]:
    """Start and end byte of each maximal run of non-separators in a row."""
    inside = ~sep[data]
    if not len(data):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    begins, stops = inside.copy(), inside.copy()
    begins[1:] &= ~inside[:-1]
    stops[:-1] &= ~inside[1:]
    cuts = offsets[1:-1]
    cuts = cuts[(cuts > 0) & (cuts < len(data))]
    begins[cuts] = inside[cuts]
    stops[cuts - 1] = inside[cuts - 1]
    return np.flatnonzero(begins), np.flatnonzero(stops) + 1


def span_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, fold: bool = True) -> np.ndarray:
    """64-bit hash of each byte span, the same wherever the span stands."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    b, inv = powers(len(data))
    acc = np.zeros(len(data) + 1, np.uint64)
    np.cumsum((_FOLDED if fold else _PLAIN)[data] * b, out=acc[1:])
    return mix((acc[ends] - acc[starts]) * inv[starts])


def row_counts(starts: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Boundaries by row among ascending positions: row r has [b[r], b[r+1])."""
    return np.searchsorted(starts, offsets)


_K = mix(np.arange(11, 19, dtype=np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F)) | np.uint64(1)


def shingles(hashes: np.ndarray, bounds: np.ndarray, width: int = 5) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each row; short rows give one shingle."""
    out: list[np.ndarray] = []
    n = len(hashes)
    if n >= width:
        rolled = np.zeros(n - width + 1, np.uint64)
        for j in range(width):
            rolled += hashes[j : n - width + 1 + j] * _K[j]
        rolled = mix(rolled)
    for lo, hi in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
        if hi - lo >= width:
            out.append(np.unique(rolled[lo : hi - width + 1]))
        elif hi > lo:
            short = hashes[lo:hi] * _K[: hi - lo]
            out.append(mix(np.array([(int(short.sum(dtype=np.uint64)) + 0x51ED27 * (hi - lo)) & _M64], np.uint64)))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def text_shingles(column: pa.Array, width: int = 5):
    """(row, sorted distinct shingle hashes) for each row of a text column."""
    data, offsets = utf8(column)
    for lo, hi in blocks(offsets):
        part, off = data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]
        starts, ends = words(part, off)
        sets = shingles(span_hashes(part, starts, ends), row_counts(starts, off), width)
        yield from zip(range(lo, hi), sets, strict=True)


def segments(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Indices starts[i], ..., starts[i]+lengths[i]-1 for all i, concatenated."""
    total = int(lengths.sum())
    if not total:
        return np.zeros(0, np.int64)
    keep = lengths > 0
    starts, lengths = starts[keep], lengths[keep]
    step = np.ones(total, np.int64)
    at = np.cumsum(lengths)[:-1]
    step[0] = starts[0]
    step[at] = starts[1:] - starts[:-1] - lengths[:-1] + 1
    return np.cumsum(step)


def binary_column(parts: list[np.ndarray]) -> pa.Array:
    """A binary column from arrays."""
    return pa.array([p.tobytes() for p in parts], pa.binary())
