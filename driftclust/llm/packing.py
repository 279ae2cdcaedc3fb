"""Best-fit packing with Martello-Toth dominance reduction.

Sequences hold ``capacity`` tokens. A longer document is cut into full pieces
and one first piece that may be shorter, so what has to be packed are pieces of
1 to capacity tokens, and all that matters of them is how many there are of each
length: a histogram of ``capacity`` counts, however many documents there are.
The driver reduces and packs the histogram; a sequence layout used many times is
one row. Every piece then finds its place by its rank among the pieces of its
length, without any piece being collected.

Reduction: a set of pieces that can share a sequence is fixed for good when it
dominates every other way to use a sequence with its first piece. For a piece
and the room beside it these are: the piece alone if nothing fits; the piece
with the largest fitting one, if that fills the room, if no two others fit
together, or if no three fit and no two are longer together; the piece with the
two that fill the room best, if no three fit, one of the two is the largest that
fits, and no two other pieces both longer than the shorter one fit. Each fixing
shrinks the instance and may allow the next. What remains is packed best-fit,
longest first. Should best fit alone do with fewer sequences, its packing counts.

Null texts are empty documents: the end id alone. Repeated doc_ids keep their
pieces, each its own row. Extra columns aren't read; an empty table packs to an
empty result.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import tokens
from .scratch import lean, materialise, prepare


def pieces(docs: DataFrame, path: str, capacity: int = 1024, end_id: int = 2, passed: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 of each piece."""
    prepare(docs.sparkSession)

    def cut(batches):
        enc = tokens.encoder(path)
        for batch in batches:
            ids, off = tokens.with_end(*enc.encode(batch.column("text")), end_id)
            n = np.diff(off)
            count = -(-n // capacity)
            row = np.repeat(np.arange(len(n)), count)
            piece = np.arange(len(row)) - np.repeat(np.cumsum(count) - count, count)
            first = n - (count - 1) * capacity
            start = np.where(piece == 0, 0, first[row] + (piece - 1) * capacity)
            length = np.where(piece == 0, first[row], capacity)
            raw, at = ids.astype("<u4").tobytes(), off[row] + start
            crc = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(at.tolist(), (at + length).tolist(), strict=True)]
            kept = [batch.column(c).take(pa.array(row)) for c in ("doc_id",)]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(piece.astype(np.int32)), pa.array(start), pa.array(length), pa.array(crc, pa.int64())], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select("doc_id", "text").mapInArrow(lean(cut), "doc_id long, piece int, start long, length long, ids_crc32 long")


def _dominant(count: np.ndarray, a: int, room: int) -> tuple[int, ...] | None:
    """The pieces beside one of length ``a`` in a set that dominates all others,
    or None; ``count`` is without that piece."""
    present = np.flatnonzero(count[: room + 1])
    if not len(present):
        return ()
    largest = int(present[-1])
    if largest == room:
        return (largest,)
    least = np.repeat(present[:3], np.minimum(count[present[:3]], 3))[:3]
    if len(least) < 2 or least[:2].sum() > room:
        return (largest,)
    if len(least) == 3 and least.sum() <= room:
        return None
    # Exactly two fit at most: the pair that fills the room best.
    below = np.zeros(room + 1, np.int64)
    below[present] = present
    below = np.maximum.accumulate(below)
    partner = below[room - present]
    twin = (partner == present) & (count[present] < 2)
    partner[twin] = below[present[twin] - 1]
    sums = np.where(partner > 0, present + partner, 0)
    best = int(sums.max())
    if largest >= best:
        return (largest,)
    if sums[-1] < best:
        return None
    second = int(partner[-1])
    between = present[present > second]
    copies = count[between] - (between == largest)
    rest = np.repeat(between, np.minimum(copies, 2))[:2]
    return (largest, second) if len(rest) < 2 or rest.sum() > room else None


def reduce(count: np.ndarray, capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Layouts fixed by dominance; their pieces are taken off ``count``."""
    out: list[tuple[tuple[int, ...], int]] = []
    for a in range(capacity, 0, -1):
        while count[a]:
            count[a] -= 1
            beside = _dominant(count, a, capacity - a)
            count[a] += 1
            if beside is None:
                break
            lengths = (a, *beside)
            # Which set is fixed depends on which lengths are left and on whether
            # there are one, two or three of one: it stays as long as three are.
            times = min(int(count[x] - 3) // lengths.count(x) for x in set(lengths)) if beside else int(count[a])
            times = max(1, times)
            out.append((lengths, times))
            for x in lengths:
                count[x] -= times
    return out


def best_fit(count: np.ndarray, capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Layouts of best fit, longest first: each piece goes to the fullest open
    sequence with room for it, which is then the one that the next like it goes
    to, as long as it has room."""
    levels: list[dict[tuple[int, ...], int]] = [{} for _ in range(capacity + 1)]
    open_levels = np.zeros(capacity + 1, bool)
    for a in range(capacity, 0, -1):
        left = int(count[a])
        while left:
            full = np.flatnonzero(open_levels[: capacity - a + 1])
            level = int(full[-1]) if len(full) else 0
            lengths, times = next(iter(levels[level].items())) if level else ((), left)
            put = min((capacity - level) // a, left)
            used = min(times, left // put)
            if level:
                if times == used:
                    del levels[level][lengths]
                    open_levels[level] = bool(levels[level])
                else:
                    levels[level][lengths] = times - used
            grown, new = (*lengths, *(a,) * put), level + a * put
            levels[new][grown] = levels[new].get(grown, 0) + used
            open_levels[new] = True
            left -= put * used
    return [(lengths, times) for level in levels for lengths, times in level.items()]


def layouts(histogram: np.ndarray, capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """(lengths in a sequence, number of such sequences), fixed ones first.

    histogram[l] is the number of pieces of length l, for l up to capacity.
    """
    count = histogram.astype(np.int64).copy()
    count[0] = 0
    plain = best_fit(count, capacity)
    reduced = reduce(count, capacity) + best_fit(count, capacity)
    total = lambda found: sum(times for _, times in found)
    return reduced if total(reduced) <= total(plain) else plain


def places(histogram: np.ndarray, capacity: int) -> list[tuple[int, int, int, int, int]]:
    """(length, first rank, last rank, first sequence, offset): ranks in a row
    of a length go to sequences in a row, at the same offset."""
    rank = np.zeros(capacity + 1, np.int64)
    rows, sequence = [], 0
    for lengths, times in layouts(histogram, capacity):
        offset = 0
        for x in lengths:
            rows.append((x, int(rank[x]), int(rank[x]) + times - 1, sequence, offset))
            rank[x] += times
            offset += x
        sequence += times
    return rows


def pack(cut: DataFrame, capacity: int = 1024) -> DataFrame:
    """``cut`` (with length) plus sequence_id and offset.

    Ranks within a length are counted by task first, so no length's pieces meet
    in one place; the layout table is bounded by the capacity and broadcast.
    """
    spark = cut.sparkSession
    cut = materialise(cut.withColumn("__task", F.spark_partition_id()), "pieces")
    sums = cut.groupBy("length", "__task").agg(F.count("*").alias("n"))
    sums = materialise(sums, "piece-counts")
    histogram = np.zeros(capacity + 1, np.int64)
    for r in sums.groupBy("length").agg(F.sum("n").alias("n")).collect():
        histogram[r.length] = r.n
    rows = places(histogram, capacity) or [(0, 0, -1, 0, 0)]
    table = spark.createDataFrame(rows, "p_length long, lo long, hi long, first long, at long")
    before = Window.partitionBy("length").orderBy("__task").rowsBetween(Window.unboundedPreceding, -1)
    base = sums.select(F.col("length").alias("b_length"), F.col("__task").alias("b_task"), F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    inside = Window.partitionBy("length", "__task").orderBy("doc_id", "piece", "ids_crc32")
    ranked = cut.withColumn("__rank", F.row_number().over(inside) - 1)
    ranked = ranked.join(base, (F.col("length") == F.col("b_length")) & (F.col("__task") == F.col("b_task"))).withColumn("__rank", F.col("__rank") + F.col("base"))
    placed = ranked.join(F.broadcast(table), (F.col("length") == F.col("p_length")) & F.col("__rank").between(F.col("lo"), F.col("hi")))
    mine = [c for c in cut.columns if not c.startswith("__")]
    return placed.select(*mine, (F.col("first") + F.col("__rank") - F.col("lo")).alias("sequence_id"), F.col("at").alias("offset"))


def pack_documents(docs: DataFrame, path: str | None = None, capacity: int = 1024, end_id: int = 2) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    return pack(pieces(docs, path or tokens.default_path(), capacity, end_id), capacity)
