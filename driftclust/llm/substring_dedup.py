"""Removal of repeated byte strings with suffix arrays.

Every byte covered by a string of ``depth`` bytes that also starts elsewhere, in
another text or the same, is removed. A corpus has no room for one suffix array,
so equal strings are brought together first: in every window of depth bytes the
smallest hash of its ``GRAM``-byte pieces marks an anchor, which depends on the
window's content alone, so equal strings have equal anchors at equal places.
Anchors that occur once need no further look. For the others the bytes around,
all that strings with this anchor can cover, are sent to one place by anchor,
two of each distinct surrounding at most, and a suffix array of the gathered
bytes, two-stage sorted, with its adjacent common prefixes says which strings
repeat. What holds for a surrounding holds for all of its places. Anchors with
very many different surroundings are dealt out again by the bytes on either
side, of which equal strings share one at least.

Null is empty text. Rows that are alike in id and text are copies of each other.
Texts shorter than depth are left alone. Extra columns are ignored; an empty
table gives an empty result.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import bloom, kernels
from .scratch import materialise, prepare
from .suffix_array import reaches, suffix_array, window_hashes

GRAM = 100
#: Bytes gathered for one suffix array, unless one anchor alone has more.
CHUNK = 1 << 20
#: Distinct surroundings from which an anchor is dealt out again.
CROWDED = 1000
_PLACE = (1 << 27) - 1


def _mins(values: np.ndarray, width: int) -> np.ndarray:
    """Least value of each run of ``width`` values."""
    n = len(values)
    if n < width:
        return np.zeros(0, values.dtype)
    padded = np.full(-(-n // width) * width, np.iinfo(values.dtype).max, values.dtype)
    padded[:n] = values
    grid = padded.reshape(-1, width)
    ahead = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].reshape(-1)
    behind = np.minimum.accumulate(grid, axis=1).reshape(-1)
    return np.minimum(ahead[: n - width + 1], behind[width - 1 : n])


def anchors(data: np.ndarray, offsets: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(row, place in row, anchor hash, surrounding's hash) of all anchors."""
    empty = np.zeros(0, np.int64)
    none = (empty, empty, empty.astype(np.uint64), empty.astype(np.uint64))
    if len(data) < depth:
        return none
    b, inv = kernels.powers(len(data) + 1)
    acc = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(kernels._PLAIN[data] * b[:-1], out=acc[1:])
    gram = kernels.mix((acc[GRAM:] - acc[:-GRAM]) * inv[: len(data) - GRAM + 1])
    least = _mins((gram & ~np.uint64(_PLACE)) | np.arange(len(gram), dtype=np.uint64), depth - GRAM + 1)
    long = np.flatnonzero(np.diff(offsets) >= depth)
    inside = kernels.segments(offsets[long], np.diff(offsets)[long] - depth + 1)
    at = np.unique(least[inside] & np.uint64(_PLACE)).astype(np.int64)
    row = np.searchsorted(offsets, at, side="right") - 1
    lo, hi = np.maximum(at - (depth - GRAM), offsets[row]), np.minimum(at + depth, offsets[row + 1])
    around = kernels.mix((acc[hi] - acc[lo]) * inv[lo] + np.uint64(0x9E3779B97F4A7C15) * (at - lo).astype(np.uint64) + (hi - at).astype(np.uint64))
    return row, at - offsets[row], gram[at], around


def _scan(docs: DataFrame, depth: int) -> DataFrame:
    def find(batches):
        for batch in batches:
            data, offsets = kernels.utf8(batch.column("text"))
            uid = batch.column("uid").to_numpy(zero_copy_only=False)
            for lo, hi in kernels.blocks(offsets):
                row, at, h, ctx = anchors(data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo], depth)
                if len(row):
                    yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(ctx.view(np.int64)), pa.array(uid[lo:hi][row]), pa.array(at)], ["h", "ctx", "uid", "at"])

    return docs.select("uid", "text").mapInArrow(find, "h long, ctx long, uid long, at long")


def _picked(docs: DataFrame, ids: DataFrame):
    """(rows whose uid may be among ``ids``, the rest), by a bounded filter."""
    words = bloom.build(ids, bloom.size_bits(ids.count(), max_bits=1 << 27))
    shared = docs.sparkSession.sparkContext.broadcast(words)

    @F.arrow_udf("boolean")
    def maybe(uid: pa.Array) -> pa.Array:
        return pa.array(bloom.contains(shared.value, uid.to_numpy(zero_copy_only=False).view(np.uint64)))

    tested = docs.withColumn("maybe", maybe("uid"))
    return tested.where("maybe").drop("maybe"), tested.where(~F.col("maybe")).drop("maybe")


def _surroundings(texts: DataFrame, depth: int) -> DataFrame:
    """(route, h, ctx, uid, at, rn, lead, bytes) for each listed anchor."""
    side = (depth - GRAM) // 2

    def cut(batches):
        for batch in batches:
            out = []
            data, offsets = kernels.utf8(batch.column("text"))
            for r, (uid, listed) in enumerate(zip(batch.column("uid").to_pylist(), batch.column("listed").to_pylist(), strict=True)):
                text = data[offsets[r] : offsets[r + 1]].tobytes()
                for x in listed:
                    at = x["at"]
                    lo, hi = max(0, at - (depth - GRAM)), min(len(text), at + depth)
                    rest = (x["h"], x["ctx"], uid, at, x["rn"], at - lo, text[lo:hi])
                    if not x["crowded"]:
                        out.append((x["h"], *rest))
                        continue
                    for mark, part in ((b"<", text[max(0, at - side) : at]), (b">", text[at + GRAM : at + GRAM + side])):
                        if len(part) == side:
                            key = hashlib.blake2b(mark + part + x["h"].to_bytes(8, "little", signed=True), digest_size=8).digest()
                            out.append((int.from_bytes(key, "little", signed=True), *rest))
                while len(out) >= 2000:
                    yield _batch(out[:2000])
                    out = out[2000:]
            if out:
                yield _batch(out)

    def _batch(rows):
        cols = list(zip(*rows, strict=True))
        return pa.RecordBatch.from_arrays([*(pa.array(c, pa.int64()) for c in cols[:7]), pa.array(cols[7], pa.binary())], ["route", "h", "ctx", "uid", "at", "rn", "lead", "bytes"])

    return texts.mapInArrow(cut, "route long, h long, ctx long, uid long, at long, rn long, lead long, bytes binary")


def repeated(rows: list[tuple], depth: int) -> list[tuple[int, int, int, int]]:
    """(h, ctx, from, to), relative to the anchor, of strings that repeat.

    rows: (h, ctx, uid, at, rn, lead, bytes). Overlapping surroundings of one
    text are laid over each other first: a place is no copy of itself. Of rows
    alike in id and text the second counts as another text.
    """
    seen: set[tuple] = set()
    spots = []
    for h, ctx, uid, at, rn, lead, raw in rows:
        key = (uid, h, at, rn)
        if key in seen:
            continue
        twin = (uid, h, at) in seen
        seen |= {key, (uid, h, at)}
        spots.append((uid, twin, at - lead, at - lead + len(raw), raw, h, ctx, at, rn))
    spots.sort(key=lambda s: s[:4])
    parts, base, size, valid, breaks = [], [], 0, [], []
    who, reach, home = None, -1, 0
    for uid, twin, lo, hi, raw, *_ in spots:
        if who == (uid, twin) and lo <= reach:
            fresh = raw[reach - lo :] if hi > reach else b""
        else:
            if who is not None:
                parts.append(b"\0")
                breaks.append(size)
                size += 1
            who, reach, home, fresh = (uid, twin), lo, size - lo, raw
        parts.append(fresh)
        size += len(fresh)
        reach = max(reach, hi)
        base.append(home)
        valid.append((home + lo, home + hi - depth + 1))
    text = np.frombuffer(b"".join(parts) + b"\0", np.uint8)
    usable = np.zeros(len(text) + 1, np.int32)
    for lo, hi in valid:
        if hi > lo:
            usable[lo] += 1
            usable[hi] -= 1
    usable = np.cumsum(usable[:-1]) > 0
    breaks = np.array([*breaks, size])
    hashes = window_hashes(text, depth, breaks[np.searchsorted(breaks, np.arange(len(text)))])
    sa = suffix_array(text, depth, hashes, usable)
    sa = sa[usable[sa]]
    same = reaches(text, sa, depth, hashes)
    marked = np.zeros(len(text) + 1, bool)
    marked[sa[same]] = True
    marked[sa[np.flatnonzero(same) - 1]] = True
    out = []
    for (_, _, lo, hi, _, h, ctx, at, rn), home in zip(spots, base, strict=True):
        a, b = home + lo, home + hi - depth + 1
        if rn != 1 or b <= a:
            continue
        m = np.concatenate([[False], marked[a:b], [False]])
        edge = np.flatnonzero(m[1:] != m[:-1])
        out += [(h, ctx, int(s) + lo - at, int(e) - 1 + lo + depth - at) for s, e in zip(edge[::2], edge[1::2], strict=True)]
    return out


def spans(docs: DataFrame, depth: int = 400) -> tuple[DataFrame, DataFrame]:
    """(docs with uid, uid -> spans): what to remove from each text."""
    prepare(docs.sparkSession)
    docs = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).withColumn("uid", F.xxhash64("doc_id", "text"))
    found = _scan(docs, depth)
    by_h = Window.partitionBy("h").orderBy("ctx", "uid", "at")
    in_ctx = Window.partitionBy("h", "ctx").orderBy("uid", "at")
    found = found.select("h", "ctx", "uid", "at", F.row_number().over(in_ctx).alias("rn"), F.lag("ctx").over(by_h).alias("p"), F.lead("ctx").over(by_h).alias("q"))
    found = materialise(found.where("p is not null or q is not null").drop("p", "q"), "anchors")
    kinds = found.where("rn = 1").groupBy("h").count().where(F.col("count") >= CROWDED).select(F.col("h").alias("ch"), F.lit(True).alias("crowded"))
    listed = found.where("rn <= 2").join(kinds, F.col("h") == F.col("ch"), "left").withColumn("crowded", F.coalesce("crowded", F.lit(False))).drop("ch")
    listed = materialise(listed.groupBy("uid").agg(F.collect_list(F.struct("h", "ctx", "at", "rn", "crowded")).alias("listed")), "anchor-lists")
    texts, _ = _picked(docs.select("uid", "text").where(F.octet_length("text") >= depth), listed.select("uid"))
    around = _surroundings(texts.join(listed, "uid").dropDuplicates(["uid"]).select("uid", "text", "listed"), depth)

    def sort(batches):
        rows, size, last = [], 0, None
        for batch in batches:
            cols = [batch.column(c).to_pylist() for c in ("route", "h", "ctx", "uid", "at", "rn", "lead", "bytes")]
            for route, *row in zip(*cols, strict=True):
                if route != last and size > CHUNK:
                    yield from _result(repeated(rows, depth))
                    rows, size = [], 0
                last = route
                rows.append(tuple(row))
                size += len(row[-1])
        if rows:
            yield from _result(repeated(rows, depth))

    def _result(found):
        if found:
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*found, strict=True)], ["h", "ctx", "lo", "hi"])

    n = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    told = around.repartition(n, "route").sortWithinPartitions("route", "uid", "at").mapInArrow(sort, "h long, ctx long, lo long, hi long")
    told = told.groupBy("h", "ctx", "lo", "hi").agg(F.lit(1).alias("one")).drop("one")
    placed = found.join(told, ["h", "ctx"]).select("uid", F.struct((F.col("at") + F.col("lo")).alias("lo"), (F.col("at") + F.col("hi")).alias("hi")).alias("span"))
    return docs, materialise(placed.groupBy("uid").agg(F.collect_set("span").alias("spans")), "spans")


def _merged(found) -> tuple[np.ndarray, np.ndarray]:
    """Maximal runs of the union of spans."""
    found = sorted((s["lo"], s["hi"]) for s in found)
    lo, hi = [], []
    for a, b in found:
        if hi and a <= hi[-1]:
            hi[-1] = max(hi[-1], b)
        else:
            lo.append(a)
            hi.append(b)
    return np.array(lo, np.int64), np.array(hi, np.int64)


def removed(docs: DataFrame, depth: int = 400) -> DataFrame:
    """doc_id, kept (the remaining bytes), n_bytes, n_removed, n_spans."""
    return _apply(docs, depth, digest=False)


def digests(docs: DataFrame, depth: int = 400) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256."""
    return _apply(docs, depth, digest=True)


def _apply(docs: DataFrame, depth: int, digest: bool) -> DataFrame:
    docs, found = spans(docs, depth)
    some, others = _picked(docs, found.select("uid"))
    last = "kept_sha256" if digest else "kept"

    def strip(batches):
        for batch in batches:
            data, offsets = kernels.utf8(batch.column("text"))
            n_removed, n_spans, kept = [], [], []
            for r, found in enumerate(batch.column("spans").to_pylist()):
                text = data[offsets[r] : offsets[r + 1]]
                lo, hi = _merged(found or [])
                keep = np.ones(len(text), bool)
                for a, b in zip(lo.tolist(), hi.tolist(), strict=True):
                    keep[a:b] = False
                left = text[keep].tobytes() if len(lo) else text.tobytes()
                n_removed.append(len(text) - len(left))
                n_spans.append(len(lo))
                kept.append(hashlib.sha256(left).hexdigest() if digest else left)
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), pa.array(np.diff(offsets)), pa.array(n_removed, pa.int64()), pa.array(n_spans, pa.int64()), pa.array(kept, pa.string() if digest else pa.binary())],
                ["doc_id", "n_bytes", "n_removed", "n_spans", last],
            )

    cut = some.join(found, "uid", "left").select("doc_id", "text", "spans").mapInArrow(strip, f"doc_id long, n_bytes long, n_removed long, n_spans long, {last} {'string' if digest else 'binary'}")
    bytes_ = F.encode("text", "UTF-8")
    whole = others.select("doc_id", F.octet_length("text").cast("long").alias("n_bytes"), F.lit(0).cast("long").alias("n_removed"), F.lit(0).cast("long").alias("n_spans"), (F.sha2(bytes_, 256) if digest else bytes_).alias(last))
    return cut.unionByName(whole)
