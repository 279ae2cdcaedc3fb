"""N-gram Jaccard join with adaptive multi-match prefixes.

Texts become sets of hashed word shingles; equal sets are one class. All sets
are ordered alike: by estimated frequency, rare first, then by hash. Sets of
Jaccard similarity t or more share ``l`` shingles of their prefixes of
n - ceil(t n) + l, for every l; with two lengths the smaller l counts. Each
class picks the l that makes its estimated cost least: longer prefixes cost more
rows, and demand more shared shingles before a pair is verified.

A prefix shingle that at most ``CROWD`` classes share gives its pairs, a bounded
number for each of its rows; pairs that come up often enough are verified. Pairs
that share a more frequent shingle are never written out: classes meet in blocks
of about ``BLOCK_CLASSES``, each class with those of its most frequent shingle
and its band of sizes, and a worker compares the classes of one block, or of two blocks that
share a frequent shingle in bands whose sizes can link, and returns only links
that tie components together. Blocks and sets are written once, to files of the
shared folder; a pair of blocks is a row that says where they stand, and its
worker reads them there, so pairs cost no disk.
Blocks are compared with themselves first; two blocks whose classes are all in
one component by then are not compared. Shingles that the frequency sketch
already knows to be frequent are never gathered by shingle at all.

Frequencies come from a sketch of bounded size over all texts; it only orders
and routes, so collisions in it cost time, never links. Null or empty texts have
no shingles and link with nothing; a text with fewer words than the width is one
shingle. Rows with a repeated doc_id are documents of their own that share the
id; extra columns are ignored (or pass through ``keep_one``); an empty table
gives an empty result.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import bloom, kernels
from .files import open_store, task_name
from .graph import components
from .scratch import lean, materialise, new_dir, prepare, release, remove

#: Least and most bits of a cell's number, and the shingles of a cell that are
#: aimed at in between.
SKETCH_BITS = (22, 25)
CELL_LOAD = 4
_PART = 1 << 16
MAX_MATCHES = 8
#: Classes of a shingle up to which its pairs are written out.
CROWD = 16
#: Frequency class (see ``frequency_classes``) of 255 or more, from which a
#: shingle's rows are not gathered.
KNOWN_CROWD = 16
#: Classes and shingles of a block, on average.
BLOCK_CLASSES = 256
BLOCK_SHINGLES = 1 << 19
#: Up to this many rows of classes to be compared are sent to all tasks that
#: read texts; beyond, the texts picked out by the filter are shuffled.
BROADCAST_ROWS = 500_000
#: Matches that a worker lays out at once.
MATCHES = 1 << 21
#: Bytes read from files that a task keeps for the next pair.
HELD_BYTES = 1 << 24


def sketch_bits(octets: int) -> int:
    """Bits for texts of so many bytes, a shingle for about six of them."""
    return min(max(math.ceil(math.log2(max(octets, 1) / 6 / CELL_LOAD)), SKETCH_BITS[0]), SKETCH_BITS[1])


def frequency_classes(docs: DataFrame, width: int) -> np.ndarray:
    """Frequency class (2 log2 of the estimate) of each cell; a cell
    is numbered by a shingle's first bits, which are more for larger inputs: an
    overfull sketch tells no shingle from another.

    Every task adds up its own cells, cells are added by ranges of 65,536, and
    32 MB at most come to the driver whatever the input. The mean load of a cell is taken
    off, so that only shingles that stand out count as frequent.
    """
    bits = sketch_bits(docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0)
    shift = np.uint64(64 - bits)

    def count(batches):
        total = np.zeros(1 << bits, np.uint16)

        def flush(held):
            cells, n = np.unique(np.concatenate(held), return_counts=True)
            total[cells] = np.minimum(total[cells] + n, 65535)

        for batch in batches:
            held, size = [], 0
            for _, s in kernels.text_shingles(batch.column(0), width):
                held.append((s >> shift).astype(np.uint32))
                size += len(s)
                if size > 1 << 18:
                    flush(held)
                    held, size = [], 0
            if held:
                flush(held)
        for p in range(0, len(total), _PART):
            part = total[p : p + _PART]
            if part.any():
                kind, some = np.uint8 if part.max() < 256 else np.uint16, part > 0
                yield pa.RecordBatch.from_arrays([pa.array([p // _PART], pa.int32()), pa.array([np.dtype(kind).itemsize], pa.int32()), pa.array([np.packbits(some).tobytes() + part[some].astype(kind).tobytes()], pa.binary())], ["p", "size", "cells"])

    def add(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(_PART, np.int64)
        for batch in batches:
            for size, cells in zip(batch.column("size").to_pylist(), batch.column("cells").to_pylist(), strict=True):
                some = np.unpackbits(np.frombuffer(cells, np.uint8, _PART // 8)).astype(bool)
                total[some] += np.frombuffer(cells, {1: np.uint8, 2: np.uint16}[size], offset=_PART // 8)
        yield pa.RecordBatch.from_arrays([pa.array([key[0].as_py()], pa.int32()), pa.array([int(total.sum())]), pa.array([np.round(8 * np.log2(1 + total)).clip(0, 255).astype(np.uint8).tobytes()], pa.binary())], ["p", "n", "cells"])

    rows = docs.select("text").mapInArrow(lean(count), "p int, size int, cells binary").groupBy("p").applyInArrow(add, "p int, n long, cells binary").collect()
    logs, seen = np.zeros(1 << bits, np.uint8), 0
    for r in rows:
        logs[r.p * _PART : (r.p + 1) * _PART] = np.frombuffer(bytes(r.cells), np.uint8)
        seen += r.n
    mean = seen / (1 << bits)
    counts = np.exp2(np.arange(256) / 8) - 1
    return np.floor(2 * np.log2(1 + np.maximum(0, counts - mean - 3 * np.sqrt(mean)))).astype(np.uint8)[logs]


def class_id(s: np.ndarray) -> int:
    """64-bit id of a set of shingles, from its hashes and its size."""
    h = kernels.mix(s * np.uint64(0x2545F4914F6CDD1D) + np.uint64(len(s)))
    return int(kernels.mix(np.array([h.sum(dtype=np.uint64)], np.uint64)).view(np.int64)[0])


def least_overlap(n: int, percent: int) -> int:
    return -(-n * percent // 100)


def prefix(s: np.ndarray, classes: np.ndarray, percent: int) -> tuple[int, np.ndarray, int]:
    """(l, prefix, how many of it aren't known to be frequent), by estimated cost."""
    n = len(s)
    kind = classes[(s >> np.uint64(65 - len(classes).bit_length())).astype(np.int64)]
    order = np.argsort(kind, kind="stable")
    need = least_overlap(n, percent)
    most = min(MAX_MATCHES, need)
    ahead = kind[order[: n - need + most]]
    others = np.cumsum(np.exp2(ahead / 2.0) - 1)
    l = np.arange(1, most + 1)  # noqa: E741
    length = n - need + l
    cost = length + others[length - 1] * (1 + n / (8 * l))
    best = int(np.argmin(cost))
    return best + 1, s[order[: length[best]]], int(np.searchsorted(ahead[: length[best]], KNOWN_CROWD))


def signatures(docs: DataFrame, classes: np.ndarray, width: int, percent: int) -> DataFrame:
    """doc_id, cid, n, l, rare, prefix (binary hashes) of each document."""
    shared = docs.sparkSession.sparkContext.broadcast(classes)

    def sign(batches):
        for batch in batches:
            rows = []
            for _, s in kernels.text_shingles(batch.column("text"), width):
                l, p, rare = prefix(s, shared.value, percent) if len(s) else (0, s, 0)  # noqa: E741
                rows.append((class_id(s) if len(s) else 0, len(s), l, rare, p.tobytes()))
            if rows:
                cols = [pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary()), strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *cols], ["doc_id", "cid", "n", "l", "rare", "prefix"])

    return docs.select("doc_id", "text").mapInArrow(lean(sign), "doc_id long, cid long, n long, l int, rare int, prefix binary")


def _among(spark, words: np.ndarray):
    """A column function: whether a class id may be among those of the filter."""
    shared = spark.sparkContext.broadcast(words)

    @F.arrow_udf("boolean")
    def maybe(cid: pa.Array) -> pa.Array:
        return pa.array(bloom.contains(shared.value, cid.to_numpy(zero_copy_only=False).view(np.uint64)))

    return maybe


def _one_each(signed: DataFrame) -> DataFrame:
    """One row of each class. Only rows of classes that may repeat are shuffled."""
    maybe = _among(signed.sparkSession, bloom.build(signed.select("cid"), bloom.size_bits(signed.count(), max_bits=1 << 27), least=2))
    tested = signed.where("n > 0").withColumn("maybe", maybe("cid"))
    some = tested.where("maybe")
    first = some.groupBy("cid").agg(F.min("doc_id").alias("first_id"))
    kept = some.alias("s").join(first.alias("f"), (F.col("s.cid") == F.col("f.cid")) & F.col("s.doc_id").eqNullSafe(F.col("f.first_id")), "left_semi").dropDuplicates(["cid", "doc_id"])
    return tested.where(~F.col("maybe")).unionByName(kept).drop("maybe")


def _tokens(signed: DataFrame) -> DataFrame:
    """(token, cid, known, what): a row for each prefix shingle.

    ``what`` holds n, l and the place in the prefix from 1, in 32, 4 and 28 bits;
    ``known`` says whether the sketch knows the shingle to be frequent.
    """

    def spread(batches):
        for batch in batches:
            raw = batch.column("prefix").to_pylist()
            cid, n, l, rare = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("cid", "n", "l", "rare"))
            k = np.array([len(p) // 8 for p in raw])
            lo = 0
            while lo < len(raw):
                hi = max(lo + 1, int(np.searchsorted(np.cumsum(k[lo:]), 1 << 16, side="right")) + lo)
                at = np.repeat(np.arange(lo, hi), k[lo:hi])
                pos = kernels.segments(np.ones(hi - lo, np.int64), k[lo:hi])
                what = (n[at] << 32) | (l[at].astype(np.int64) << 28) | pos
                yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(b"".join(raw[lo:hi]), np.int64)), pa.array(cid[at]), pa.array(pos > rare[at]), pa.array(what)], ["token", "cid", "known", "what"])
                lo = hi

    return signed.select("cid", "n", "l", "rare", "prefix").mapInArrow(lean(spread), "token long, cid long, known boolean, what long")


def _bounds(np_, nq, lp, lq, percent: int):
    """(must share, least matches): what a pair of sizes has to share, and how
    many shingles of how long prefixes that makes; both own prefixes are long
    enough for these."""
    alpha = ((np_ + nq) * percent + 99 + percent) // (100 + percent)
    need = lambda n: (n * percent + 99) // 100
    return alpha, np.minimum(lp + (alpha - need(np_)) // 2, lq + (alpha - need(nq)) // 2)


def _shared(rows: DataFrame, percent: int) -> DataFrame:
    """(token, a, b, what): pairs a < b with the least matches in ``what`` and no
    token, for each shingle that few share; (token, class, null, what) for each
    class of the others."""

    def gather(batches):
        held, size, crowd = [], 0, None
        for batch in batches:
            held.append([batch.column(c).to_numpy(zero_copy_only=False) for c in ("token", "cid", "what")])
            size += batch.num_rows
            if size < 1 << 16:
                continue
            token, cid, what = (np.concatenate(c) for c in zip(*held, strict=True))
            cut = int(np.searchsorted(token, token[-1]))
            yield from told(token[:cut], cid[:cut], what[:cut], crowd)
            if len(token) - cut > CROWD or token[-1] == crowd:
                # Too many to be pairs: what is still to come is, too.
                if cut:
                    crowd = None
                yield crowded(token[cut:], cid[cut:], what[cut:])
                crowd, cut = token[-1], len(token)
            held, size = [[token[cut:], cid[cut:], what[cut:]]], len(token) - cut
        if held:
            yield from told(*(np.concatenate(c) for c in zip(*held, strict=True)), crowd)

    def crowded(token, cid, what):
        return pa.RecordBatch.from_arrays([pa.array(token), pa.array(cid), pa.nulls(len(cid), pa.int64()), pa.array(what)], ["token", "a", "b", "what"])

    def told(token, cid, what, crowd):
        if not len(token):
            return
        first = np.flatnonzero(np.concatenate([[True], token[1:] != token[:-1]]))
        count = np.diff(np.append(first, len(token)))
        large = (count > CROWD) | (token[first] == crowd if crowd is not None else False)
        if large.any():
            at = kernels.segments(first[large], count[large])
            yield crowded(token[at], cid[at], what[at])
        for g in range(2, CROWD + 1):
            these = first[(count == g) & ~large]
            i, j = np.triu_indices(g, 1)
            step = max(1, MATCHES // (8 * len(i)))
            for lo in range(0, len(these), step):
                p, q = ((these[lo : lo + step, None] + x).ravel() for x in (i, j))
                (n_p, l_p, at_p), (n_q, l_q, at_q) = ((w >> 32, (w >> 28) & 15, w & ((1 << 28) - 1)) for w in (what[p], what[q]))
                alpha, least = _bounds(n_p, n_q, l_p, l_q, percent)
                fit = (n_p * 100 >= n_q * percent) & (n_q * 100 >= n_p * percent) & (at_p <= n_p - alpha + least) & (at_q <= n_q - alpha + least)
                if fit.any():
                    a, b = cid[p[fit]], cid[q[fit]]
                    yield pa.RecordBatch.from_arrays([pa.nulls(len(a), pa.int64()), pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b)), pa.array(least[fit])], ["token", "a", "b", "what"])

    n = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return rows.where("not known").select("token", "cid", "what").repartition(n, "token").sortWithinPartitions("token").mapInArrow(lean(gather), "token long, a long, b long, what long")


def _overlaps(left: list[np.ndarray], right: list[np.ndarray]) -> np.ndarray:
    """How many elements each set of ``left`` shares with each of ``right``."""
    out = np.zeros((len(left), len(right)), np.int64)
    token = np.concatenate([np.zeros(0, np.uint64), *right])
    owner = np.repeat(np.arange(len(right)), [len(s) for s in right])
    order = np.argsort(token, kind="stable")
    token, owner = token[order], owner[order]
    for i, s in enumerate(left):
        lo, hi = np.searchsorted(token, s, side="left"), np.searchsorted(token, s, side="right")
        ends = np.cumsum(hi - lo)
        at = 0
        while at < len(s):  # parts of one set that lay out a bounded number of matches
            stop = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + MATCHES, side="right")))
            out[i] += np.bincount(owner[kernels.segments(lo[at:stop], (hi - lo)[at:stop])], minlength=len(right))
            at = stop
    return out


def _fits(n_p, n_q, percent: int) -> np.ndarray:
    return (n_p * 100 >= n_q * percent) & (n_q * 100 >= n_p * percent)


def _keep(rows: DataFrame, told, name: str) -> tuple[DataFrame, str]:
    """(key, file, at, size) of the pairs (key, bytes) that ``told`` makes of
    batches of ``rows``, and the shared folder whose files hold the bytes.

    Only files that the index names count: a task that is run again writes another.
    """
    folder = new_dir(rows.sparkSession, name)
    fs, place = open_store(folder)
    fs.create_dir(place, recursive=True)

    def save(batches):
        fs, place = open_store(folder)
        file, out, at, index = task_name("part", ".bin"), None, 0, []
        for key, raw in told(batches):
            if out is None:
                out = fs.open_output_stream(f"{place}/{file}")
            out.write(raw)
            index.append((key, at, len(raw)))
            at += len(raw)
        if out is not None:
            out.close()
            key, start, size = (pa.array(c, pa.int64()) for c in zip(*index, strict=True))
            yield pa.RecordBatch.from_arrays([key, pa.array([file] * len(index)), start, size], ["key", "file", "at", "size"])

    return materialise(rows.mapInArrow(lean(save), "key long, file string, at long, size long"), f"{name}-index"), folder


class _Kept:
    """Reads what ``_keep`` wrote; the last parts read, and some files, stay at hand."""

    def __init__(self, folder: str, parse):
        self.fs, self.place = open_store(folder)
        self.parse, self.files, self.parts, self.held = parse, {}, {}, 0

    def get(self, file: str, at: int, size: int):
        part = self.parts.pop((file, at), None)
        if part is None:
            if file not in self.files:
                if len(self.files) >= 64:
                    self.files.pop(next(iter(self.files))).close()
                self.files[file] = self.fs.open_input_file(f"{self.place}/{file}")
            part = (size, self.parse(self.files[file].read_at(size, at)))
            self.held += size
        self.parts[file, at] = part
        while self.held > HELD_BYTES and len(self.parts) > 1:
            self.held -= self.parts.pop(next(iter(self.parts)))[0]
        return part[1]

    def close(self) -> None:
        for f in self.files.values():
            f.close()


def _sides(rows: DataFrame, kernel, payload: tuple[str, ...], schema: str, folder: str | None = None) -> DataFrame:
    """``kernel`` on the classes of each pair of blocks, a list for either side;
    the second is None where ``block`` is ``other``. Rows have block, other,
    side, cid, root and ``payload``, of which the last column is binary hashes;
    with ``folder``, the payload is where these stand in it."""

    def meet(batches):
        kept = _Kept(folder, lambda raw: np.frombuffer(raw, np.uint64)) if folder else None
        sides, key = ([], []), None
        for batch in batches:
            if kept:
                for block, other, side, *own, file, at, size in zip(*(batch.column(c).to_pylist() for c in ("block", "other", "side", "cid", "root", *payload)), strict=True):
                    if (block, other) != key:
                        yield from told(sides, key)
                        sides, key = ([], []), (block, other)
                    sides[side].append((*own, kept.get(file, at, size)))
                continue
            hashes = batch.column(payload[-1])
            for i, (block, other, side, *own) in enumerate(zip(*(batch.column(c).to_pylist() for c in ("block", "other", "side", "cid", "root", *payload[:-1])), strict=True)):
                if (block, other) != key:
                    yield from told(sides, key)
                    sides, key = ([], []), (block, other)
                sides[side].append((*own, np.frombuffer(hashes[i].as_py(), np.uint64)))
        yield from told(sides, key)
        if kept:
            kept.close()

    def told(sides, key):
        alone = key is not None and key[0] == key[1]
        if sides[0] and (alone or sides[1]):
            found = kernel(key, sides[0], None if alone else sides[1])
            if found:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*found, strict=True)], names)

    names = [c.split()[0] for c in schema.split(", ")]
    n = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return rows.repartition(n, "block", "other").sortWithinPartitions("block", "other", "side").select("block", "other", "side", "cid", "root", *payload).mapInArrow(lean(meet), schema)


def _share(key, left, right, percent: int) -> list[tuple]:
    """(*key, side, cid, root) of the classes (cid, root, n, l, prefix) that share
    enough with one of another root on the other side."""
    other = left if right is None else right
    _, r_p, n_p, l_p, s_p = zip(*left, strict=True)
    _, r_q, n_q, l_q, s_q = zip(*other, strict=True)
    n_p, l_p = np.array(n_p)[:, None], np.array(l_p)[:, None]
    _, least = _bounds(n_p, np.array(n_q), l_p, np.array(l_q), percent)
    maybe = (_overlaps(s_p, s_q) >= least) & _fits(n_p, np.array(n_q), percent) & (np.array(r_p)[:, None] != np.array(r_q))
    out = [(*key, 0, *left[i][:2]) for i in np.flatnonzero(maybe.any(axis=1))]
    return out if right is None else out + [(*key, 1, *other[j][:2]) for j in np.flatnonzero(maybe.any(axis=0))]


_CANDIDATES = "block long, other long, side long, cid long, root long"


def _candidates(rows: DataFrame, prefixes: DataFrame, percent: int) -> DataFrame:
    """(block, other, side, cid, root) of ``rows`` whose prefix shares enough
    with that of a class of another root on the other side."""
    return _sides(rows.join(prefixes, "cid"), lambda key, left, right: _share(key, left, right, percent), ("n", "l", "prefix"), _CANDIDATES)


def _pack(members: list[tuple]) -> bytes:
    """Bytes of the classes (cid, root, n, l, prefix in bytes) of a block."""
    head = np.array([(*m[:4], len(m[4])) for m in members], np.int64)
    return b"".join([np.int64(len(members)).tobytes(), head.tobytes(), *(m[4] for m in members)])


def _unpack(raw: bytes) -> list[tuple]:
    m = int(np.frombuffer(raw, np.int64, 1)[0])
    out, at = [], 8 + 40 * m
    for *own, size in np.frombuffer(raw, np.int64, 5 * m, 8).reshape(m, 5).tolist():
        out.append((*own, np.frombuffer(raw, np.uint64, size // 8, at)))
        at += size
    return out


def _candidates_of(meet: DataFrame, members: DataFrame, prefixes: DataFrame, percent: int) -> DataFrame:
    """As ``_candidates``, for each of ``meet`` (block, other); ``members`` has
    block, cid, root. Blocks go to files, pairs hold their places only."""

    def packed(batches):
        held, last = [], None
        for batch in batches:
            for block, *own in zip(*(batch.column(c).to_pylist() for c in ("block", "cid", "root", "n", "l", "prefix")), strict=True):
                if held and block != last:
                    yield last, _pack(held)
                    held = []
                last = block
                held.append(own)
        if held:
            yield last, _pack(held)

    def compare(batches):
        kept = _Kept(folder, _unpack)
        for batch in batches:
            found = []
            for block, other, *places in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                left = kept.get(*places[:3])
                found += _share((block, other), left, None if block == other else kept.get(*places[3:]), percent)
            if found:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*found, strict=True)], [c.split()[0] for c in _CANDIDATES.split(", ")])
        kept.close()

    n = int(meet.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = members.select("block", "cid", "root").join(prefixes, "cid").repartition(n, "block").sortWithinPartitions("block")
    index, folder = _keep(rows.select("block", "cid", "root", "n", "l", "prefix"), packed, "block-files")
    a, b = (index.select(F.col("key").alias(key), *(F.col(c).alias(f"{c}_{x}") for c in ("file", "at", "size"))) for key, x in (("block", "p"), ("other", "q")))
    pairs = meet.join(a, "block").join(b, "other").select("block", "other", *(f"{c}_{x}" for x in "pq" for c in ("file", "at", "size")))
    found = materialise(pairs.repartition(n, "block", "other").sortWithinPartitions("block", "other").mapInArrow(lean(compare), _CANDIDATES), "candidates")
    remove(meet.sparkSession, folder)
    release(index)
    return found


def _with_sets(meet: DataFrame, docs: DataFrame, reps: DataFrame, width: int) -> tuple[DataFrame, DataFrame, str]:
    """``meet`` (block, other, side, cid, root) with file, at and size: where the
    class's set stands in a shared folder; the index and the folder.

    Sets are made again from the texts of the classes' first documents, which a
    filter of bounded size picks out of the scan; each is written once.
    """
    targets = materialise(meet.select("cid").distinct().join(reps, "cid").select("cid", F.col("doc_id").alias("rep")), "targets")
    rows = targets.count()
    among = _among(docs.sparkSession, bloom.build(targets.select(F.xxhash64("rep").alias("h")), bloom.size_bits(rows, max_bits=1 << 27)))
    texts = docs.select("doc_id", "text").where(among(F.xxhash64("doc_id")))
    told = texts.join(F.broadcast(targets) if rows <= BROADCAST_ROWS else targets, F.col("doc_id").eqNullSafe(F.col("rep")))

    def sets(batches):
        for batch in batches:
            cid = batch.column("cid").to_pylist()
            for r, s in kernels.text_shingles(batch.column("text"), width):
                if len(s) and class_id(s) == cid[r]:
                    yield cid[r], s.tobytes()

    index, folder = _keep(told.select("cid", "text"), sets, "set-files")
    release(targets)
    return meet.join(index.dropDuplicates(["key"]), F.col("cid") == F.col("key")).drop("key"), index, folder


def _links(meet: DataFrame, docs: DataFrame, reps: DataFrame, width: int, percent: int, name: str) -> DataFrame:
    """Links (a, b) between classes of two sides that tie all linked classes of
    different roots together."""
    rows, index, folder = _with_sets(meet, docs, reps, width)

    def verify(key, left, right):
        other = left if right is None else right
        n_p, n_q = np.array([[len(s)] for *_, s in left]), np.array([len(s) for *_, s in other])
        both = _overlaps([s for *_, s in left], [s for *_, s in other])
        linked = 100 * both >= percent * (n_p + n_q - both)
        parent: dict[int, int] = {}

        def find(x: int) -> int:
            while parent.setdefault(x, x) != x:
                parent[x] = x = parent[parent[x]]
            return x

        out = []
        for i, j in np.argwhere(linked).tolist():
            (a, ra, _), (b, rb, _) = left[i], other[j]
            ra, rb = find(ra), find(rb)
            if ra != rb:
                parent[ra] = rb
                out.append((a, b))
        return out

    links = materialise(_sides(rows, verify, ("file", "at", "size"), "a long, b long", folder), name)
    remove(docs.sparkSession, folder)
    release(index)
    return links


def _cut(members: DataFrame, *keys: str) -> DataFrame:
    """``members`` (cid, n, keys) plus block, together (classes of its keys) and
    whole (whether these are one block)."""
    size = members.groupBy(*(F.col(k).alias(f"of_{k}") for k in keys)).agg(F.greatest(F.ceil(F.count("*") / BLOCK_CLASSES), F.ceil(F.sum("n") / BLOCK_SHINGLES)).alias("blocks"), F.count("*").alias("together"))
    same = [F.col(k).eqNullSafe(F.col(f"of_{k}")) for k in keys]
    cut = members.join(size, same).select(*members.columns, "blocks", "together")
    return cut.withColumn("block", F.xxhash64(*keys, F.pmod(F.xxhash64("cid"), F.col("blocks")))).withColumn("whole", F.col("blocks") == 1).drop("blocks")


def link(docs: DataFrame, width: int = 5, percent: int = 80) -> tuple[DataFrame, DataFrame]:
    """(members, roots): doc_id, cid, n of all rows; node, root of linked classes."""
    prepare(docs.sparkSession)
    classes = frequency_classes(docs, width)
    signed = materialise(signatures(docs, classes, width, percent), "signatures")
    members = materialise(signed.select("doc_id", "cid", "n"), "members")
    ones = _one_each(signed)
    reps = materialise(ones.select("cid", "doc_id"), "classes")
    rows = _tokens(ones)
    shared = materialise(_shared(rows, percent), "shared-shingles")
    # Frequent shingles: the ones found, and those that the sketch knows.
    hot = shared.where("token is not null").select("token", F.col("a").alias("cid"), "what").unionByName(rows.where("known").select("token", "cid", "what"))
    hot = hot.select("token", "cid", F.shiftright("what", 32).alias("n"))
    # Sets that link are in one band of sizes, or in neighbouring ones.
    hot = hot.withColumn("band", F.floor(F.log("n") / math.log(100 / percent) + 1e-6).cast("int"))
    often = hot.groupBy("token", "band").agg(F.count("*").alias("g"))
    hot = materialise(hot.join(often, ["token", "band"]), "frequent-shingles")
    few = shared.where("token is null").groupBy("a", "b").agg(F.count("*").alias("m"), F.first("what").alias("least")).where("m >= least").select("a", "b")
    few = materialise(few, "pairs")
    release(shared)
    home = hot.groupBy("cid").agg(F.first("n").alias("n"), F.first("band").alias("band"), F.max_by("token", F.struct("g", "token")).alias("home"))
    blocks = materialise(_cut(home, "home", "band"), "blocks")
    among = _among(docs.sparkSession, bloom.build(blocks.select("cid"), bloom.size_bits(blocks.count(), max_bits=1 << 27)))
    prefixes = materialise(ones.select("cid", "n", "l", "prefix").where(among("cid")), "prefixes")
    release(signed)
    # First the pairs, each class with its partners, and the blocks by themselves.
    alone = blocks.where("together > 1").select("block", F.col("block").alias("other"), F.lit(0).cast("long").alias("side"), "cid", F.col("cid").alias("root"))
    lead = few.select(F.col("a").alias("block"), F.bitwise_not("a").alias("other"), F.lit(0).cast("long").alias("side"), F.col("a").alias("cid"), F.col("a").alias("root")).distinct()
    rest = few.select(F.col("a").alias("block"), F.bitwise_not("a").alias("other"), F.lit(1).cast("long").alias("side"), F.col("b").alias("cid"), F.col("b").alias("root"))
    meet = materialise(_candidates(alone, prefixes, percent).unionByName(lead).unionByName(rest), "candidates")
    links = _links(meet, docs, reps, width, percent, "links")
    roots = materialise(components(links), "roots")
    release(few, meet)
    # Then blocks that share a frequent shingle: the large components of a
    # shingle's classes make blocks of their own, which needn't meet each other.
    known = blocks.join(roots, F.col("cid") == F.col("node"), "left").select("cid", "n", "home", "band", F.col("whole").alias("met"), F.coalesce("root", "cid").alias("root"))
    large = known.groupBy("home", "band", "root").agg(F.count("*").alias("size")).where(F.col("size") * 4 >= BLOCK_CLASSES).select("home", "band", "root", F.col("root").alias("kin"))
    again = materialise(_cut(known.join(large, ["home", "band", "root"], "left"), "home", "band", "kin"), "blocks")
    side = hot.select("token", "cid").join(again, "cid").select("token", "block", "home", "band", "kin", "met").distinct()
    p, q = (side.select("token", *(F.col(c).alias(f"{c}_{x}") for c in ("block", "home", "band", "kin", "met"))) for x in "pq")
    apart = ~F.coalesce(F.col("kin_p") == F.col("kin_q"), F.lit(False)) & ~((F.col("home_p") == F.col("home_q")) & (F.col("band_p") == F.col("band_q")) & F.col("met_p"))
    apart &= F.abs(F.col("band_p") - F.col("band_q")) <= 1
    meet = p.join(q, "token").where((F.col("block_p") < F.col("block_q")) & apart).select(F.col("block_p").alias("block"), F.col("block_q").alias("other")).distinct()
    meet = meet.unionByName(again.where("kin is null and not met").select("block", F.col("block").alias("other")).distinct())
    meet = materialise(meet, "block-pairs")
    found = _candidates_of(meet, again, prefixes, percent)
    more = _links(found, docs, reps, width, percent, "more-links")
    release(hot, blocks, meet, found, prefixes)
    if more.isEmpty():
        return members, roots
    joined = components(roots.select(F.col("node").alias("a"), F.col("root").alias("b")).unionByName(more))
    return members, materialise(joined, "roots")


def near_copies(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id of every row of ``docs`` (doc_id, text)."""
    members, roots = link(docs, width, percent)
    per_class = members.where("n > 0").groupBy("cid").agg(F.min("doc_id").alias("first_id"))
    per_class = per_class.join(roots, per_class["cid"] == roots["node"], "left").select("cid", "first_id", F.coalesce("root", "cid").alias("root"))
    per_root = per_class.groupBy("root").agg(F.min("first_id").alias("component_id"))
    named = per_class.join(per_root, "root").select("cid", "component_id")
    full = members.where("n > 0").join(named, "cid").select("doc_id", F.col("n").alias("n_shingles"), "component_id")
    return full.unionByName(members.where("n = 0").select("doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id")))


def keep_one(docs: DataFrame, width: int = 5, percent: int = 80, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` with one document of each component, its smallest doc_id; all
    documents without shingles stay."""
    slim = docs.select(F.col(key).alias("doc_id"), F.col(text).alias("text"))
    out = near_copies(slim, width, percent).where(~F.col("doc_id").eqNullSafe(F.col("component_id"))).select(F.col("doc_id").alias("__drop")).distinct()
    out = materialise(out, "near-copies")
    return docs.join(out, docs[key] == out["__drop"], "left_anti")
