"""Token-id files: frequency-ranked ids in a byte-aligned variable-length code.

Ids are replaced by their rank by corpus frequency (most frequent: 0), so that
most take one byte. A rank takes 1 to 4 bytes; the lengths stand apart, two bits
each, in control bytes for four ids. Decoding looks the control bytes up in a
256-row table of lengths and the ranks up in the rank table.

File format, little-endian: ``VBTOKEN1``; u32 number of ranks; u32 id by rank;
then frames until the end of the file. Frame: u64 documents, ids, control bytes,
data bytes; i64 doc_id, u32 id count of each document; control bytes; data
bytes. Each document's ids end with ``end_id``. Files hold ascending doc_id and
follow each other in the order of the manifest's ``part``.

Texts are encoded once: their ids, with the text where a doc_id may be repeated,
are what is counted, sorted and written.

Null text is empty: its row is the end id alone. Null ids come first and are
written as the smallest long. Repeated doc_ids keep a row each, ordered by the
text. Extra columns aren't read; an empty table writes no file.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import bloom, tokens
from .files import open_store, task_name
from .scratch import lean, materialise, new_dir, prepare, release

MAGIC = b"VBTOKEN1"
#: Ids of a frame: what a reader and a writer hold at once.
FRAME_IDS = 1 << 20
LENGTHS = ((np.arange(256)[:, None] >> (2 * np.arange(4))) & 3).astype(np.uint8) + 1


def pack(ranks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(control bytes, data bytes) of the ranks."""
    v = ranks.astype(np.uint32)
    size = 1 + (v > 0xFF).astype(np.uint8) + (v > 0xFFFF) + (v > 0xFFFFFF)
    padded = np.zeros(-(-len(v) // 4) * 4, np.uint8)
    padded[: len(v)] = size - 1
    control = np.bitwise_or.reduce(padded.reshape(-1, 4) << np.array([0, 2, 4, 6], np.uint8), axis=1).astype(np.uint8)
    raw = v.view(np.uint8).reshape(-1, 4) if v.dtype.byteorder != ">" else v.byteswap().view(np.uint8).reshape(-1, 4)
    return control, raw[np.arange(4) < size[:, None]]


def unpack(control: np.ndarray, data: np.ndarray, n: int) -> np.ndarray:
    """The n ranks that ``pack`` took."""
    size = LENGTHS[control].reshape(-1)[:n].astype(np.int64)
    at = np.cumsum(size) - size
    out = data[at].astype(np.uint32) if n else np.zeros(0, np.uint32)
    for k in range(1, 4):
        more = np.flatnonzero(size > k)
        if not len(more):
            break
        out[more] |= data[at[more] + k].astype(np.uint32) << np.uint32(8 * k)
    return out


def encoded(docs: DataFrame, path: str, end_id: int) -> DataFrame:
    """doc_id, tie, size, ids of all rows: ids with the end id, of 2 or 4 bytes
    (size) each. tie is the text where the doc_id may be repeated, else null."""
    spark = docs.sparkSession
    repeated = bloom.build(docs.select(F.xxhash64("doc_id").alias("h")), bloom.size_bits(docs.count(), max_bits=1 << 27), least=2)
    shared = spark.sparkContext.broadcast(repeated)

    def encode(batches):
        enc = tokens.encoder(path)
        for batch in batches:
            ids, off = tokens.with_end(*enc.encode(batch.column("text")), end_id)
            kind = np.dtype("<u2" if ids.max(initial=0) < 1 << 16 else "<u4")
            raw, edge = ids.astype(kind).tobytes(), (off * kind.itemsize).tolist()
            maybe = bloom.contains(shared.value, batch.column("h").to_numpy().view(np.uint64))
            tie = pc.if_else(pa.array(maybe), batch.column("text"), pa.scalar(None, batch.column("text").type))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), tie, pa.array(np.full(batch.num_rows, kind.itemsize, np.int32)), pa.array([raw[a:b] for a, b in zip(edge[:-1], edge[1:], strict=True)], pa.binary())], ["doc_id", "tie", "size", "ids"])

    rows = docs.select("doc_id", "text", F.xxhash64("doc_id").alias("h"))
    return materialise(rows.mapInArrow(lean(encode), "doc_id long, tie string, size int, ids binary"), "token-ids", "zstd")


def _flat(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    """All ids of a batch of ``encoded``, and its rows' offsets into them."""
    size, raw = batch.column("size").to_numpy(), batch.column("ids").to_pylist()
    parts = [np.frombuffer(r, "<u2" if s == 2 else "<u4") for r, s in zip(raw, size.tolist(), strict=True)]
    return np.concatenate(parts).astype(np.int64), np.concatenate([[0], np.cumsum([len(p) for p in parts])])


def ranking(rows: DataFrame) -> np.ndarray:
    """Ids by falling count over all rows of ``encoded``, ties by id; bounded by
    the vocabulary."""

    def count(batches):
        total = np.zeros(1 << 16, np.int64)
        for batch in batches:
            if batch.num_rows:
                n = np.bincount(_flat(batch)[0], minlength=len(total))
                n[: len(total)] += total
                total = n
        used = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(used), pa.array(total[used])], ["id", "n"])

    counts = rows.select("size", "ids").mapInArrow(lean(count), "id long, n long").groupBy("id").agg(F.sum("n").alias("n"))
    return np.array([r.id for r in counts.orderBy(F.desc("n"), "id").collect()], np.uint32)


def write(docs: DataFrame, folder: str, path: str, end_id: int = 0) -> DataFrame:
    """Write all documents below ``folder``; returns the manifest of the files.

    Manifest: part, file, n_docs, n_ids. Only files named in it belong to the
    output: a task that is run again writes another file.
    """
    spark = docs.sparkSession
    prepare(spark)
    docs = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63))).alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    rows = encoded(docs, path, end_id)
    by_rank = ranking(rows)
    shared = spark.sparkContext.broadcast(by_rank)
    fs, place = open_store(folder)
    fs.create_dir(place, recursive=True)

    def save(batches):
        from pyspark import TaskContext

        by_rank = shared.value
        rank_of = np.zeros(max(int(by_rank.max(initial=0)), end_id) + 1, np.uint32)
        rank_of[by_rank] = np.arange(len(by_rank), dtype=np.uint32)
        fs, place = open_store(folder)
        name, out = task_name("ids", ".vbt"), None
        n_docs = n_ids = 0
        for batch in batches:
            if not batch.num_rows:
                continue
            if out is None:
                out = fs.open_output_stream(f"{place}/{name}")
                out.write(MAGIC + struct.pack("<I", len(by_rank)) + by_rank.astype("<u4").tobytes())
            keys = batch.column("doc_id").to_numpy()
            ids, off = _flat(batch)
            lo = 0
            while lo < len(keys):
                hi = max(lo + 1, int(np.searchsorted(off, off[lo] + FRAME_IDS, side="right")) - 1)
                part = ids[off[lo] : off[hi]]
                control, data = pack(rank_of[part])
                out.write(struct.pack("<4Q", hi - lo, len(part), len(control), len(data)))
                for a in (keys[lo:hi].astype("<i8"), np.diff(off[lo : hi + 1]).astype("<u4"), control, data):
                    out.write(a.tobytes())
                lo = hi
            n_docs, n_ids = n_docs + len(keys), n_ids + len(ids)
        if out is not None:
            out.close()
            yield pa.RecordBatch.from_arrays([pa.array([TaskContext.get().partitionId()]), pa.array([name]), pa.array([n_docs]), pa.array([n_ids])], ["part", "file", "n_docs", "n_ids"])

    spread = rows.repartitionByRange("doc_id").sortWithinPartitions("doc_id", "tie").select("doc_id", "size", "ids")
    manifest = materialise(spread.mapInArrow(lean(save), "part long, file string, n_docs long, n_ids long"), "token-manifest")
    release(rows)
    return manifest


def frames(stream):
    """(doc ids, id counts, ids) of each frame of an open file."""
    if stream.read(8) != MAGIC:
        raise ValueError("not a token-id file")
    (n,) = struct.unpack("<I", stream.read(4))
    by_rank = np.frombuffer(stream.read(4 * n), "<u4")
    while head := stream.read(32):
        docs, ids, n_control, n_data = struct.unpack("<4Q", head)
        keys, counts = np.frombuffer(stream.read(8 * docs), "<i8"), np.frombuffer(stream.read(4 * docs), "<u4")
        control, data = np.frombuffer(stream.read(n_control), np.uint8), np.frombuffer(stream.read(n_data), np.uint8)
        yield keys, counts, by_rank[unpack(control, data, ids)]


def read(manifest: DataFrame, folder: str, digest: bool = False) -> DataFrame:
    """doc_id, start, n_tokens and the ids (binary u32), or their crc32.

    start counts the ids of all documents before; it comes from running sums of
    the manifest, one row a file.
    """
    placed = manifest.withColumn("base", F.sum("n_ids").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)))
    placed = placed.select("file", F.coalesce("base", F.lit(0)).alias("base"))
    n = max(1, min(manifest.count(), 10_000))

    def load(batches):
        fs, place = open_store(folder)
        for batch in batches:
            for name, base in zip(batch.column("file").to_pylist(), batch.column("base").to_pylist(), strict=True):
                with fs.open_input_stream(f"{place}/{name}") as stream:
                    for keys, counts, ids in frames(stream):
                        edge = np.concatenate([[0], np.cumsum(counts, dtype=np.int64)])
                        raw = ids.astype("<u4").tobytes()
                        each = [raw[4 * a : 4 * b] for a, b in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True)]
                        last = pa.array([zlib.crc32(x) for x in each], pa.int64()) if digest else pa.array(each, pa.binary())
                        yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array(base + edge[:-1]), pa.array(counts.astype(np.int64)), last], ["doc_id", "start", "n_tokens", "ids_crc32" if digest else "ids"])
                        base += int(edge[-1])

    return placed.repartition(n).mapInArrow(load, f"doc_id long, start long, n_tokens long, {'ids_crc32 long' if digest else 'ids binary'}")


def round_trip(docs: DataFrame, path: str | None = None, end_id: int = 0) -> DataFrame:
    """Write the documents and read their ids back, as digests."""
    path = path or tokens.default_path()
    folder = new_dir(docs.sparkSession, "token-files")
    return read(write(docs, folder, path, end_id), folder, digest=True)
