"""Chunks of controlled imbalance by two-layer random sampling.

Layer one draws how many clusters a chunk has and integer ratios between them;
layer two draws that many objects of each. Draws come from integer arithmetic on
ids, so they are the same on any number of tasks, after any retry, and in SQL.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: A linear congruential step modulo 2^31.
MUL, ADD, MOD = 1103515245, 12345, 2147483648


def lcg(v: Column) -> Column:
    return F.pmod(F.pmod(v, F.lit(MOD)) * MUL + ADD, F.lit(MOD))


def draw_number(chunk: Column, i: Column, seed: int) -> Column:
    """Pseudo-random integer below 2^31 for a chunk and a position."""
    return lcg(lcg(lcg(chunk + F.lit(seed)) + i * 7919) + 104729)


def sizes(points: DataFrame) -> DataFrame:
    """label, source_n, pos: clusters from the smallest on, ties by label."""
    n = points.groupBy("label").agg(F.count("*").alias("source_n"))
    return n.withColumn("pos", F.row_number().over(Window.orderBy("source_n", "label")))


def plan(points: DataFrame, chunks: int, ratio: int, seed: int = 1, base: str = "source", k_chunk: int = 0) -> DataFrame:
    """chunk_id, label, pos, source_n, ratio, target_n for every chunk.

    base="source" multiplies a ratio with the source size of the cluster before,
    "chunk" with the size that it got. k_chunk fixes the number of clusters.
    """
    spark = points.sparkSession
    src = sizes(points)
    total = src.agg(F.count("*").alias("k_star"))
    ids = spark.range(chunks).select(F.col("id").alias("chunk_id")).crossJoin(F.broadcast(total))
    drawn = F.lit(k_chunk) if k_chunk else F.when(F.col("k_star") > 1, 2 + draw_number(F.col("chunk_id"), F.lit(0), seed) % F.greatest(F.col("k_star") - 1, F.lit(1))).otherwise(F.lit(1))
    ids = ids.withColumn("k", F.least(drawn, F.col("k_star")))
    ratios = F.array_sort(F.transform(F.sequence(F.lit(1), F.greatest(F.col("k") - 1, F.lit(1)).cast("int")), lambda i: 1 + draw_number(F.col("chunk_id"), i.cast("long"), seed) % ratio))
    rows = ids.withColumn("ratios", ratios).join(F.broadcast(src), F.col("pos") <= F.col("k"))
    rows = rows.withColumn("ratio", F.when(F.col("pos") == 1, F.lit(1).cast("long")).otherwise(F.element_at("ratios", F.greatest(F.col("pos") - 1, F.lit(1)).cast("int"))))
    by_chunk = Window.partitionBy("chunk_id").orderBy("pos")
    if base == "source":
        before = F.lag("source_n").over(by_chunk)
        target = F.when(F.col("pos") == 1, F.col("source_n")).otherwise(F.least(F.col("ratio") * before, F.col("source_n")))
        return rows.withColumn("target_n", target).select("chunk_id", "label", "pos", "source_n", "ratio", "target_n")
    so_far = F.array_sort(F.collect_list(F.struct("pos", "ratio", "source_n")).over(by_chunk.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    folded = F.aggregate(so_far, F.lit(0).cast("long"), lambda acc, r: F.when(r["pos"] == 1, r["source_n"]).otherwise(F.least(acc * r["ratio"], r["source_n"])))
    return rows.withColumn("target_n", folded).select("chunk_id", "label", "pos", "source_n", "ratio", "target_n")


def draw(points: DataFrame, planned: DataFrame, seed: int = 1) -> DataFrame:
    """Points of each chunk, without replacement inside it: those of a label with
    the lowest draws. The plan is a few rows a chunk and is broadcast."""
    pts = points.drop("chunk_id").join(F.broadcast(planned.select("chunk_id", "label", "target_n")), "label")
    order = Window.partitionBy("chunk_id", "label").orderBy(draw_number(F.col("obj_id") + F.col("chunk_id") * 31, F.lit(3), seed), "obj_id")
    return pts.withColumn("__r", F.row_number().over(order)).where(F.col("__r") <= F.col("target_n")).select("chunk_id", "obj_id", "x", "label")


def stream(points: DataFrame, chunks: int, ratio: int, seed: int = 1, **options) -> DataFrame:
    return draw(points, plan(points, chunks, ratio, seed, **options), seed)
