"""Blocked Bloom filters of bounded size, built in two passes over the data.

Pass one sends, for each 64-bit hash, its probe positions to the block that
owns them and keeps the bits that were hit; the counting form keeps only bits
that were hit at least twice. The filter has at most ``max_bits`` bits however
much data there is: beyond the rows that this suits it only grows denser, so a
reader gets more false candidates and never a missed one.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .scratch import lean

PROBES = 3
SEGMENT_BITS = 1 << 16


def size_bits(rows: int, bits_per_row: int = 16, max_bits: int = 1 << 29) -> int:
    """A power of two, from one segment to max_bits."""
    bits = SEGMENT_BITS
    while bits < rows * bits_per_row and bits < max_bits:
        bits *= 2
    return bits


def positions(hashes: np.ndarray, bits: int) -> np.ndarray:
    """(len, PROBES) bit positions, distinct for a hash in nearly all cases."""
    h = hashes.astype(np.uint64, copy=False)
    out = np.empty((len(h), PROBES), np.int64)
    step = (h >> np.uint64(33)) | np.uint64(1)
    for k in range(PROBES):
        out[:, k] = ((h + np.uint64(k) * step) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(20)) & np.uint64(bits - 1)
    return out


def contains(words: np.ndarray, hashes: np.ndarray) -> np.ndarray:
    """Whether each hash may be among those that the filter was built from."""
    hit = np.ones(len(hashes), bool)
    for column in positions(hashes, len(words) * 8).T:
        hit &= (words[column >> 3] >> (column & 7).astype(np.uint8)) & 1 == 1
    return hit


def build(hashes: DataFrame, bits: int, least: int = 1) -> np.ndarray:
    """Bytes of the filter over the only column of ``hashes`` (a long).

    least=2 keeps the bits hit by at least two rows: ``contains`` is then true
    for every hash that occurs twice. A map task holds the positions of its own
    rows and sends two bytes for each, a reduce task holds one segment, and the
    driver gets bits / 8 bytes, which max_bits bounds.
    """
    name = hashes.columns[0]

    def partial(batches):
        kept = [np.zeros(0, np.int64)]
        for batch in batches:
            p = positions(batch.column(0).to_numpy(zero_copy_only=False).view(np.uint64), bits)
            p.sort(axis=1)
            kept += [p[:, 0], *(p[p[:, k] != p[:, k - 1], k] for k in range(1, PROBES))]
        found, count = np.unique(np.concatenate(kept), return_counts=True)
        segment, offset = found // SEGMENT_BITS, (found % SEGMENT_BITS).astype(np.uint16)
        ids, first = np.unique(segment, return_index=True)
        edges = [*first.tolist(), len(found)]
        rows = [(s, offset[lo:hi].tobytes(), offset[lo:hi][count[lo:hi] > 1].tobytes()) for s, lo, hi in zip(ids.tolist(), edges[:-1], edges[1:], strict=True)]
        for k in range(0, len(rows), 4096):
            seg, once, twice = zip(*rows[k : k + 4096], strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(seg, pa.int32()), pa.array(once, pa.binary()), pa.array(twice, pa.binary())], ["segment", "once", "twice"])

    def merge(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        once, twice = np.zeros(SEGMENT_BITS, bool), np.zeros(SEGMENT_BITS, bool)
        for batch in batches:
            for a, b in zip(batch.column("once").to_pylist(), batch.column("twice").to_pylist(), strict=True):
                at = np.frombuffer(a, np.uint16)
                twice[at[once[at]]] = True
                twice[np.frombuffer(b, np.uint16)] = True
                once[at] = True
        got = twice if least > 1 else once
        if got.any():
            yield pa.RecordBatch.from_arrays([pa.array([key[0].as_py()], pa.int32()), pa.array([np.packbits(got, bitorder="little").tobytes()], pa.binary())], ["segment", "word"])

    parts = hashes.select(F.col(name).cast("long")).mapInArrow(lean(partial), "segment int, once binary, twice binary")
    merged = parts.groupBy("segment").applyInArrow(merge, "segment int, word binary")
    out = np.zeros(bits // 8, np.uint8)
    for row in merged.toLocalIterator():
        out[row.segment * (SEGMENT_BITS // 8) : (row.segment + 1) * (SEGMENT_BITS // 8)] = np.frombuffer(bytes(row.word), np.uint8)
    return out
