"""Benchmark decontamination by MinHash containment search, in DataFrame functions only.

An item is in a document when at least ``threshold`` of the item's distinct
word shingles occur in it. Items are partitioned by the size of their shingle
set (powers of two). Each partition has its own sketch length: the m smallest
shingle hashes of an item, its bottom MinHash sketch, where m is one more than
the number of shingles that the largest item of the partition may miss. An item
that is contained misses fewer of its shingles than its sketch is long, so one
sketch hash at least is met in the document: the search loses nothing, however
long the document. Documents are read as a stream of shingle hashes that probe
the sketches; a pair with enough sketch hits is a
candidate, and its exact containment is counted over all of the item's shingles.

Words are runs of non-space characters, A-Z lower-cased. A text with fewer
words than ``width`` is one shingle, its whole sequence; a null or empty text
has none, contains nothing and is contained in nothing. Rows that share a
doc_id (or item_id) are one document (item) with the shingles of all of them.
Extra columns are ignored; empty tables give an empty result.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .scratch import materialise

#: Above this many rows a side is joined by shuffle instead of broadcast.
BROADCAST_ROWS = 2_000_000
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_SPACE = " \t\n\x0b\x0c\r"


def word_array(text: Column) -> Column:
    """Words of a text; an empty array for null or blank text."""
    body = F.btrim(F.translate(F.coalesce(text, F.lit("")), _UPPER, _LOWER), F.lit(_SPACE))
    return F.when(F.length(body) == 0, F.array().cast("array<string>")).otherwise(F.split(body, "[ \\t-\\r]+"))


def shingle_rows(df: DataFrame, key: str, width: int) -> DataFrame:
    """(key, sh): a row for each place of a shingle.

    The shifted copies of the word array are zipped and unnested, so hashing
    happens in generated code, row by row, after the generator. In a text of
    fewer words than ``width`` the later copies are empty: the zip pads its one
    row with nulls, which the hash passes over.
    """
    words = df.select(key, word_array(F.col("text")).alias("w"))
    places = F.greatest(F.size("w") - (width - 1), F.least(F.size("w"), F.lit(1)))
    words = words.select(key, "w", places.alias("places"))
    rows = words.select(key, F.inline(F.arrays_zip(*[F.slice("w", k + 1, F.col("places")).alias(f"w{k}") for k in range(width)])))
    return rows.select(key, F.xxhash64(*[F.col(f"`{c}`") for c in rows.columns[1:]]).alias("sh"))


def sketches(items: DataFrame, threshold: float, width: int) -> DataFrame:
    """item_id, sh, n_item, need, least_hits, in_sketch: all shingles of all items."""
    distinct = shingle_rows(items, "item_id", width).select("item_id", "sh").distinct()
    sized = distinct.withColumn("n_item", F.count("*").over(Window.partitionBy("item_id"))).withColumn("rank", F.row_number().over(Window.partitionBy("item_id").orderBy("sh")))
    permille = round(threshold * 1000)
    ceil_of = lambda n: F.floor((n * permille + 999) / 1000)
    top = F.pow(F.lit(2), F.floor(F.log2("n_item")) + 1) - 1
    length = F.least(F.col("n_item"), top - ceil_of(top) + 1)
    return sized.select(
        "item_id",
        "sh",
        "n_item",
        ceil_of(F.col("n_item")).cast("long").alias("need"),
        (length - (F.col("n_item") - ceil_of(F.col("n_item")))).cast("long").alias("least_hits"),
        (F.col("rank") <= length).alias("in_sketch"),
    )


def _bounded(df: DataFrame, rows: int) -> DataFrame:
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def matches(docs: DataFrame, items: DataFrame, threshold: float = 0.8, width: int = 5, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, item_id, n_item, n_shared, containment of each item in a document."""
    if not 0 < threshold <= 1 or math.isclose(threshold, 0):
        raise ValueError("threshold must be in (0, 1]")
    docs = docs.select(F.col(key).alias("doc_id"), F.col(text).alias("text"))
    known = materialise(sketches(items.select("item_id", "text"), threshold, width), "benchmark-shingles")
    n_known = known.count()
    probe = _bounded(known.where("in_sketch").select("item_id", "sh", "least_hits"), n_known)
    stream = shingle_rows(docs, "doc_id", width)
    found = (
        stream.join(probe, stream["sh"] == probe["sh"])
        .select("doc_id", "item_id", probe["sh"].alias("sh"), "least_hits")
        .groupBy("doc_id", "item_id", "least_hits", "sh").agg(F.lit(1).alias("one"))
        .groupBy("doc_id", "item_id", "least_hits").agg(F.count("*").alias("hits"))
        .where("hits >= least_hits")
        .select("doc_id", "item_id")
    )
    found = materialise(found, "benchmark-candidates")
    ids = found.select(F.col("doc_id").alias("cand_id")).distinct()
    if ids.count() <= BROADCAST_ROWS:
        # Written out, or the optimiser would split all texts before this join.
        docs = materialise(docs.join(F.broadcast(ids), docs["doc_id"].eqNullSafe(ids["cand_id"]), "left_semi"), "benchmark-texts")
    cand = _bounded(found.select(F.col("doc_id").alias("c_doc"), F.col("item_id").alias("c_item")), found.count())
    stream = shingle_rows(docs, "doc_id", width)
    every = _bounded(known.select("item_id", "sh", "n_item", "need"), n_known)
    shared = stream.join(every, "sh")
    shared = shared.join(cand, shared["doc_id"].eqNullSafe(cand["c_doc"]) & shared["item_id"].eqNullSafe(cand["c_item"]), "left_semi")
    return (
        shared.groupBy("doc_id", "item_id", "n_item", "need", "sh").agg(F.lit(1).alias("one"))
        .groupBy("doc_id", "item_id", "n_item", "need").agg(F.count("*").alias("n_shared"))
        .where("n_shared >= need")
        .select("doc_id", "item_id", "n_item", "n_shared", (F.col("n_shared") / F.col("n_item")).alias("containment"))
    )


def remove_contaminated(docs: DataFrame, items: DataFrame, threshold: float = 0.8, width: int = 5, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` without the documents that contain an item; columns unchanged."""
    bad = materialise(matches(docs, items, threshold, width, key, text).select(F.col("doc_id").alias("__bad")).distinct(), "benchmark-flagged")
    bad = _bounded(bad, bad.count())
    return docs.join(bad, docs[key].eqNullSafe(bad["__bad"]), "left_anti")
