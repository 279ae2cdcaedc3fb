"""Vectors and scaling, as DataFrame expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def sq_dist(a: Column, b: Column) -> Column:
    """Squared distance of two array columns."""
    return F.aggregate(F.zip_with(a, b, lambda p, q: (p - q) * (p - q)), F.lit(0.0), lambda s, v: s + v)


def dist(a: Column, b: Column) -> Column:
    return F.sqrt(sq_dist(a, b))


def by_position(df: DataFrame, by: list[str], *aggregates: tuple[str, str]) -> DataFrame:
    """Vector aggregates: (function, name) over x, by position; one row a group.

    A vector is unnested only up to the map-side sums, so what is shuffled is one
    number for each group, position and task.
    """
    flat = df.select(*by, F.posexplode("x").alias("pos", "v"))
    sums = flat.groupBy(*by, "pos").agg(*[getattr(F, f)("v").alias(n) for f, n in aggregates])
    sorted_ = F.array_sort(F.collect_list(F.struct("pos", *[n for _, n in aggregates])))
    out = sums.groupBy(*by).agg(sorted_.alias("all")) if by else sums.agg(sorted_.alias("all"))
    return out.select(*by, *[F.col(f"all.{n}").alias(n) for _, n in aggregates])


def minmax(df: DataFrame, by: list[str] | None = None) -> DataFrame:
    """x scaled to [0, 1] by position, over all rows or by group; a constant
    feature maps to 0. The bounds are one row, or one a group."""
    by = by or []
    bounds = by_position(df, by, ("min", "lo"), ("max", "hi"))
    joined = df.join(F.broadcast(bounds), by) if by else df.crossJoin(F.broadcast(bounds))
    width = F.zip_with("hi", "lo", lambda h, v: h - v)
    shifted = F.zip_with("x", "lo", lambda v, m: v - m)
    scaled = F.zip_with(shifted, width, lambda v, w: F.when(w > 0, v / w).otherwise(F.lit(0.0)))
    return joined.withColumn("x", scaled).select(*df.columns)
