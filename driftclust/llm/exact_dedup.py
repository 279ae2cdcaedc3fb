"""Exact deduplication with two-pass Bloom filtering.

Pass one builds a counting Bloom filter over the 64-bit hashes of all texts and
keeps the bits hit twice. Pass two tests each row against it: a row that the
filter rules out is unique for certain and passes straight through, only the
possibly repeated rows are shuffled, by SHA-256 of the text, which decides.

Null text counts as empty text, so nulls and empty texts are copies of each
other. A repeated doc_id is an ordinary row: copies with the same doc_id share
it as keep_id, and exactly one row of a group is kept (ties broken by nothing
but identity of id: rows equal in text and doc_id are all marked kept by
``classes`` and reduced to one by ``drop_copies``). Empty tables give empty
tables. Other columns pass through under their names, whatever they are;
columns that start with ``__`` are reserved.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import bloom
from .scratch import materialise, prepare

#: Groups of at least this share of the candidate rows are joined by broadcast:
#: at most HOT_GROUPS of them can exist.
HOT_GROUPS = 1000


def _possible(df: DataFrame, words: np.ndarray) -> DataFrame:
    """``df`` with ``__maybe``: whether its ``__h`` may occur twice."""
    shared = df.sparkSession.sparkContext.broadcast(words)

    @F.arrow_udf("boolean")
    def maybe(h: pa.Array) -> pa.Array:
        return pa.array(bloom.contains(shared.value, h.to_numpy(zero_copy_only=False).view(np.uint64)))

    return df.withColumn("__maybe", maybe("__h"))


def _keys(docs: DataFrame, text: str) -> DataFrame:
    body: Column = F.coalesce(F.col(text), F.lit(""))
    return docs.withColumn("__h", F.xxhash64(body)).withColumn("__sha", F.sha2(F.encode(body, "UTF-8"), 256))


def classes(docs: DataFrame, text: str = "text", key: str = "doc_id", max_bits: int = 1 << 27) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 and rows of ``docs`` alike.

    The row with the largest doc_id of each set of equal texts stays. Shuffled
    are (SHA-256, doc_id) of the candidates, at most; texts stay where they are.
    """
    spark = docs.sparkSession
    prepare(spark)
    base = materialise(_keys(docs, text).select(F.col(key).alias("doc_id"), "__h", "__sha"), "dedup-keys")
    rows = base.count()
    words = bloom.build(base.select("__h"), bloom.size_bits(rows, max_bits=max_bits), least=2)
    tested = _possible(base, words)
    alone = tested.where(~F.col("__maybe")).select("doc_id", F.col("doc_id").alias("keep_id"), F.lit(1).cast("long").alias("group_size"), F.lit(True).alias("kept"), F.col("__sha").alias("text_sha256"))
    some = tested.where("__maybe").select("doc_id", "__sha")
    groups = materialise(some.groupBy("__sha").agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("group_size")), "dedup-groups")
    hot = max(1000, rows // HOT_GROUPS)
    large = F.broadcast(groups.where(F.col("group_size") >= hot))
    small = groups.where(F.col("group_size") < hot)
    mine = ["doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), F.col("__sha").alias("text_sha256")]
    in_large = some.join(large, "__sha").select(*mine)
    in_small = some.join(F.broadcast(large_keys(groups, hot)), "__sha", "left_anti").join(small, "__sha").select(*mine)
    return alone.unionByName(in_large).unionByName(in_small)


def large_keys(groups: DataFrame, hot: int) -> DataFrame:
    return groups.where(F.col("group_size") >= hot).select("__sha")


def drop_copies(docs: DataFrame, text: str = "text", key: str = "doc_id", max_bits: int = 1 << 27) -> DataFrame:
    """``docs`` without copies: of equal texts the largest doc_id stays.

    Rows that the filter rules out are read, tested and written without a
    shuffle. The candidates' groups are decided on (SHA-256, doc_id), then the
    candidates alone are shuffled to meet the winners.
    """
    spark = docs.sparkSession
    prepare(spark)
    names = docs.columns
    keyed = _keys(docs, text)
    base = materialise(keyed.select(F.col(key).alias("__id"), "__h", "__sha"), "dedup-keys")
    words = bloom.build(base.select("__h"), bloom.size_bits(base.count(), max_bits=max_bits), least=2)
    some = _possible(base, words).where("__maybe")
    winners = materialise(some.groupBy("__sha").agg(F.max("__id").alias("__keep")), "dedup-winners")
    tested = _possible(keyed, words)
    alone = tested.where(~F.col("__maybe")).select(*names)
    candidates = tested.where("__maybe").withColumn("__id", F.col(key))
    # The join is on text hash and id together: the rows of one large group of
    # copies are dealt over all tasks, and one of them meets its winner.
    same = (candidates["__sha"] == winners["__sha"]) & candidates["__id"].eqNullSafe(winners["__keep"])
    stay = candidates.join(winners, same, "left_semi").dropDuplicates(["__sha", "__id"]).select(*names)
    return alone.unionByName(stay)
