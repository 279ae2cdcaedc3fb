"""Planted Gaussian mixtures on the keys of given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .sampler import lcg

#: For each set, table, key, spread, and for each cluster its
#: centre and share of the rows in thousandths.
SPECS = {
    "ga": ("part", "p_partkey", 0.06, [(0.2, 0.2, 596), (0.8, 0.2, 253), (0.2, 0.8, 121), (0.8, 0.8, 30)]),
    "id": ("orders", "o_orderkey", 0.03, [(0.5, 0.85, 406), (0.15, 0.5, 281), (0.85, 0.5, 163), (0.5, 0.15, 109), (0.5, 0.5, 41)]),
    "drift": ("events", "event_id", 0.05, [(0.2, 0.2, 596), (0.8, 0.2, 253), (0.2, 0.8, 121), (0.8, 0.8, 30)]),
    "dense": ("orders", "o_orderkey", 0.01, [(0.5, 0.5, 900), (0.2, 0.2, 100)]),
}


def normals(key, salt: int):
    """Two standard normals from a key, by two uniforms."""
    u1 = F.greatest(lcg(lcg(lcg(key * 2 + salt))) / F.lit(2147483648.0), F.lit(1e-9))
    u2 = lcg(lcg(lcg(key * 2 + 1 + salt * 3) + 77)) / F.lit(2147483648.0)
    r = F.sqrt(F.lit(-2.0) * F.ln(u1))
    return r * F.cos(F.lit(6.283185307179586) * u2), r * F.sin(F.lit(6.283185307179586) * u2)


def mixture(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """chunk_id, obj_id, x, label. drift moves centres by the day and turns the
    sizes round from day 15 on; grid is a uniform ordinal lattice."""
    if name == "grid":
        keys = spark.read.parquet(f"{sf_dir}/orders.parquet").select(F.col("o_orderkey").alias("k"))
        return keys.select(F.lit(0).cast("long").alias("chunk_id"), F.col("k").alias("obj_id"), F.array((F.col("k") % 8) / 7.0, (F.floor(F.col("k") / 8) % 8) / 7.0).alias("x"), (F.col("k") % 2).cast("int").alias("label"))
    source, key, spread, clusters = SPECS[name]
    rows = spark.read.parquet(f"{sf_dir}/{source}.parquet")
    day = F.lit(0)
    if name == "drift":
        day = F.datediff("ts", F.lit("2024-01-01"))
    k = F.col(key)
    place = lcg(lcg(k + 17)) % 1000
    if name == "drift":
        place = F.when(day < 15, place).otherwise(999 - place)
    cx, cy, label = F.lit(None).cast("double"), F.lit(None).cast("double"), F.lit(None).cast("int")
    for i, (x, y, share) in reversed(list(enumerate(clusters))):
        top = sum(c[2] for c in clusters[: i + 1])
        inside = place < top
        cx, cy, label = F.when(inside, F.lit(x)).otherwise(cx), F.when(inside, F.lit(y)).otherwise(cy), F.when(inside, F.lit(i)).otherwise(label)
    a, b = normals(k, 5)
    move = day * 0.01 if name == "drift" else F.lit(0.0)
    chunk = day.cast("long") if name == "drift" else F.lit(0).cast("long")
    return rows.select(chunk.alias("chunk_id"), k.alias("obj_id"), F.array(cx + move + a * spread, cy + b * spread).alias("x"), label.alias("label"))
