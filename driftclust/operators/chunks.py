"""Cutting tables and streams into chunks."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def by_time(df: DataFrame, ts: str = "ts", width: str = "14 hours 24 minutes", start: str = "9 hours 36 minutes") -> DataFrame:
    """chunk_id: start of the tumbling window in seconds."""
    w = F.window(F.col(ts).cast("timestamp"), width, width, start)
    return df.withColumn("chunk_id", F.unix_timestamp(w["start"]))


def by_count(df: DataFrame, key: str, n: int, buckets: int = 64) -> DataFrame:
    """chunk_id: n rows each, in order of a numeric key.

    The key's range is cut into buckets; rows are numbered inside them and the
    buckets' counts are added up, so that no window holds all rows.
    """
    lo, hi = df.agg(F.min(key), F.max(key)).first()
    if lo is None:
        return df.withColumn("chunk_id", F.lit(0).cast("long"))
    width = max(1, -(-(hi - lo + 1) // buckets))
    cut = df.withColumn("__b", ((F.col(key) - lo) / width).cast("long"))
    counts = cut.groupBy("__b").agg(F.count("*").alias("__n"))
    base = counts.select("__b", F.coalesce(F.sum("__n").over(Window.orderBy("__b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("__base"))
    inside = F.row_number().over(Window.partitionBy("__b").orderBy(key)) - 1
    return cut.join(F.broadcast(base), "__b").withColumn("chunk_id", F.floor((inside + F.col("__base")) / n)).drop("__b", "__base")


def by_mod(df: DataFrame, key: str, n: int) -> DataFrame:
    return df.withColumn("chunk_id", F.pmod(F.col(key), F.lit(n)))


def by_hash(df: DataFrame, key: str, n: int) -> DataFrame:
    return df.withColumn("chunk_id", F.pmod(F.xxhash64(key), F.lit(n)))
