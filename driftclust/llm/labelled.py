"""The labelled rows that both text classifiers learn from."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def held_out(key: Column) -> Column:
    """Rows never trained on: crc32 of the id as text is divisible by 5."""
    return F.crc32(key.cast("string")) % 5 == 0


def labelled(labels: DataFrame, label: str) -> DataFrame:
    """l_id, y of all labelled rows that aren't held out. Null labels and ids don't count."""
    ids = labels.select(F.col("doc_id").alias("l_id"), F.col(label).cast("int").alias("y")).where(F.col("l_id").isNotNull() & F.col("y").isin(0, 1))
    return ids.where(~held_out(F.col("l_id")))


def sample(docs: DataFrame, labels: DataFrame, label: str, max_rows: int) -> DataFrame:
    """doc_id, text, y of at most ``max_rows`` labelled rows that aren't held out.

    The rows with the smallest hash of doc_id are taken from the label table, so
    only ids and labels are ranked and the texts are met through a broadcast of
    at most max_rows ids. Null labels and ids don't count.
    """
    ids = labelled(labels, label).orderBy(F.xxhash64("l_id", F.lit(7)), "l_id", "y").limit(max_rows)
    texts = docs.select("doc_id", "text")
    return texts.join(F.broadcast(ids), texts["doc_id"] == ids["l_id"]).select("doc_id", "text", "y")
