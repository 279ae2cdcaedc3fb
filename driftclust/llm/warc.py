"""WARC archives, index first: write, then read selected records by byte range.

Every page is a record of its own gzip member. A page whose payload is that of
a page with a smaller page_id is a revisit record, which has the headers but not
the payload. Writing yields the index (file, offset, length, url, digest and
what the record is); reading takes any selection of index rows, sorts them by
file and offset, and turns neighbours into one read while the gap between them
is small. Payloads that are read are checked against their digest.

Null html is an empty payload, a null url an empty one; control characters in
urls are percent-encoded. Rows with the smallest page_id of a payload are all
responses, should the id repeat. A null page_id refers to nothing and is smaller
than none. Extra columns aren't read; an empty table has an empty index.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import re
import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import bloom
from .files import open_store, task_name
from .scratch import materialise, new_dir, prepare

#: High halves of record ids; the low half is the page_id.
_PAGE, _NO_PAGE = 0x6472_6966_7463_8000, 0x6472_6966_7463_8001
_LOW = (1 << 64) - 1
REVISIT = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
#: Neighbours at most so many bytes apart are read together, up to MOST bytes.
GAP, MOST = 1 << 16, 1 << 23
INDEX = "file string, offset long, length long, url string, digest string, page_id long, record_type string"


def record_id(page_id: int | None) -> str:
    high = _NO_PAGE if page_id is None else _PAGE
    return f"<urn:uuid:{uuid.UUID(int=(high << 64) | ((page_id or 0) & _LOW))}>"


def page_of(record: str) -> int | None:
    value = uuid.UUID(record.strip("<>").rpartition(":")[2]).int
    low = value & _LOW
    return None if value >> 64 == _NO_PAGE else low - (1 << 64) if low >> 63 else low


def digest_of(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record(page_id: int | None, url: str, payload: bytes, refers_to: int | None, revisit: bool, date: str) -> bytes:
    """One WARC/1.1 record as a gzip member."""
    block = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    head = ["WARC/1.1", f"WARC-Type: {'revisit' if revisit else 'response'}", f"WARC-Record-ID: {record_id(page_id)}", f"WARC-Date: {date}", f"WARC-Target-URI: {url}", f"WARC-Payload-Digest: sha1:{digest_of(payload)}"]
    if revisit:
        head += [f"WARC-Profile: {REVISIT}", f"WARC-Refers-To: {record_id(refers_to)}"]
    else:
        block += payload
    head += ["Content-Type: application/http;msgtype=response", f"Content-Length: {len(block)}"]
    squeeze = zlib.compressobj(1, zlib.DEFLATED, 31)
    return squeeze.compress("\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n") + squeeze.flush()


def parse(raw: bytes) -> tuple[dict[str, str], bytes, bytes]:
    """(WARC headers, HTTP header, payload) of one record."""
    head, _, rest = raw.partition(b"\r\n\r\n")
    lines = head.decode().split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError("no WARC record at this offset")
    fields = dict(line.split(": ", 1) for line in lines[1:])
    block = rest[: int(fields["Content-Length"])]
    http, _, payload = block.partition(b"\r\n\r\n")
    return fields, http, payload


def first_pages(pages: DataFrame) -> DataFrame:
    """page_id, url, html with first_id: the smallest page_id of the payload.

    Rows whose payload can't repeat, by a two-pass Bloom filter, aren't
    shuffled; payloads of very many pages meet a broadcast of bounded size.
    """
    spark = pages.sparkSession
    body = F.coalesce("html", F.lit(""))
    keyed = pages.select("page_id", F.coalesce("url", F.lit("")).alias("url"), body.alias("html"), F.sha1(F.encode(body, "UTF-8")).alias("sha"), F.xxhash64(body).alias("h"))
    keys = materialise(keyed.select("page_id", "sha", "h"), "page-keys")
    rows = keys.count()
    shared = spark.sparkContext.broadcast(bloom.build(keys.select("h"), bloom.size_bits(rows, max_bits=1 << 27), least=2))

    @F.arrow_udf("boolean")
    def maybe(h: pa.Array) -> pa.Array:
        return pa.array(bloom.contains(shared.value, h.to_numpy(zero_copy_only=False).view(np.uint64)))

    groups = materialise(keys.where(maybe("h")).groupBy("sha").agg(F.min("page_id").alias("first_id"), F.count("*").alias("n")), "page-groups")
    tested = keyed.withColumn("maybe", maybe("h")).drop("h")
    alone = tested.where(~F.col("maybe")).select("page_id", "url", "html", F.col("page_id").alias("first_id"))
    some = tested.where("maybe").drop("maybe")
    hot = max(1000, rows // 1000)
    many, few = groups.where(F.col("n") >= hot).select("sha", "first_id"), groups.where(F.col("n") < hot).select("sha", "first_id")
    mine = ["page_id", "url", "html", "first_id"]
    in_many = some.join(F.broadcast(many), "sha").select(*mine)
    in_few = some.join(F.broadcast(many), "sha", "left_anti").join(few, "sha").select(*mine)
    return alone.unionByName(in_many).unionByName(in_few)


def write(pages: DataFrame, folder: str, date: str = "2024-01-01T00:00:00Z") -> DataFrame:
    """Write one archive for each task below ``folder``; returns the index.

    A task that is run again writes another file; the index, written by Spark's
    commit, names only files of tasks that counted.
    """
    prepare(pages.sparkSession)
    fs, place = open_store(folder)
    fs.create_dir(place, recursive=True)

    def save(batches):
        fs, place = open_store(folder)
        name, out, at = task_name("pages", ".warc.gz"), None, 0
        for batch in batches:
            rows = []
            for page_id, url, html, first in zip(*(batch.column(c).to_pylist() for c in ("page_id", "url", "html", "first_id")), strict=True):
                if out is None:
                    out = fs.open_output_stream(f"{place}/{name}", compression=None)
                    info = b"software: driftclust\r\nformat: WARC File Format 1.1\r\n"
                    head = f"WARC/1.1\r\nWARC-Type: warcinfo\r\nWARC-Record-ID: <urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, name)}>\r\nWARC-Date: {date}\r\nContent-Type: application/warc-fields\r\nContent-Length: {len(info)}\r\n\r\n"
                    raw = gzip.compress(head.encode() + info + b"\r\n\r\n", 1, mtime=0)
                    out.write(raw)
                    at = len(raw)
                payload, revisit = html.encode(), first is not None and page_id != first
                url = re.sub(r"[\x00-\x20\x7f-\x9f  ]", lambda m: "".join(f"%{b:02X}" for b in m[0].encode()), url)
                raw = record(page_id, url, payload, first, revisit, date)
                out.write(raw)
                rows.append((name, at, len(raw), url, digest_of(payload), page_id, "revisit" if revisit else "response"))
                at += len(raw)
            if rows:
                cols = list(zip(*rows, strict=True))
                types = [pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string()]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], [x.split()[0] for x in INDEX.split(", ")])
        if out is not None:
            out.close()

    return materialise(first_pages(pages).mapInArrow(save, INDEX), "warc-index")


def read(index: DataFrame, folder: str, payloads: bool = False) -> DataFrame:
    """page_id, payload_bytes, payload_digest, record_type, refers_to (and url,
    payload, which is null for revisits) of the selected records."""

    def load(batches):
        fs, place = open_store(folder)
        name, stream, held = None, None, []

        def flush():
            if not held:
                return []
            lo, hi = held[0][0], held[-1][0] + held[-1][1]
            stream.seek(lo)
            raw = stream.read(hi - lo)
            out = []
            for offset, length in held:
                fields, http, payload = parse(gzip.decompress(raw[offset - lo : offset - lo + length]))
                digest = fields["WARC-Payload-Digest"].partition(":")[2]
                revisit = fields["WARC-Type"] == "revisit"
                if not revisit and digest_of(payload) != digest:
                    raise ValueError(f"{name}, {offset}: the payload doesn't have its digest")
                size = int(re.search(rb"\r\nContent-Length: (\d+)", http)[1])
                out.append((page_of(fields["WARC-Record-ID"]), size, digest, fields["WARC-Type"], page_of(fields["WARC-Refers-To"]) if revisit else None, fields["WARC-Target-URI"], None if revisit else payload))
            held.clear()
            return out

        def table(rows):
            cols = list(zip(*rows, strict=True))
            types = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.binary()]
            names = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "url", "payload"]
            n = 7 if payloads else 5
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols[:n], types[:n], strict=True)], names[:n])

        for batch in batches:
            for file, offset, length in zip(*(batch.column(c).to_pylist() for c in ("file", "offset", "length")), strict=True):
                if file != name:
                    if rows := flush():
                        yield table(rows)
                    name, stream = file, fs.open_input_file(f"{place}/{file}")
                elif held and (offset - held[-1][0] - held[-1][1] > GAP or offset + length - held[0][0] > MOST):
                    if rows := flush():
                        yield table(rows)
                held.append((offset, length))
        if rows := flush():
            yield table(rows)

    n = int(index.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    picked = index.select("file", "offset", "length").repartition(n, "file").sortWithinPartitions("file", "offset")
    more = ", url string, payload binary" if payloads else ""
    return picked.mapInArrow(load, f"page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long{more}")


def round_trip(pages: DataFrame) -> DataFrame:
    """Write all pages, read all records back."""
    folder = new_dir(pages.sparkSession, "warc")
    return read(write(pages, folder), folder)
