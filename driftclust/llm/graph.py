"""Connected components of an edge table, without collecting anything."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .scratch import materialise, remove


def components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(node, root): root is the smallest node that ``edges`` (a, b) connect.

    Alternating star contraction: each node hands its larger neighbours to its
    smallest one, then all of its smaller neighbours. Edges never grow in number
    beyond the input's, and depth falls geometrically. Each round is written to
    the shared folder, which cuts the lineage. Nodes without an edge to another
    node don't appear.
    """
    e = edges.where("a <> b").select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).distinct()
    e = materialise(e, "edges")
    mark = _mark(e)
    for _ in range(most_rounds):
        both = e.select(F.col("hi").alias("u"), F.col("lo").alias("v")).unionByName(e.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = e.join(least, e["lo"] == least["u"]).select("hi", F.col("m").alias("lo")).distinct()
        small = large.groupBy(F.col("hi").alias("u")).agg(F.min("lo").alias("m"))
        moved = large.join(small, large["hi"] == small["u"]).select("hi", "lo", "m")
        nxt = moved.select(F.col("lo").alias("hi"), F.col("m").alias("lo")).where("hi <> lo").unionByName(small.select(F.col("u").alias("hi"), F.col("m").alias("lo"))).distinct()
        old, e = e, materialise(nxt, "edges")
        remove(e.sparkSession, old.scratch_path)
        now = _mark(e)
        if now == mark:
            return e.select(F.col("hi").alias("node"), F.col("lo").alias("root")).unionByName(e.select(F.col("lo").alias("node"), F.col("lo").alias("root")).distinct())
        mark = now
    raise RuntimeError(f"components did not settle in {most_rounds} rounds")


def _mark(e: DataFrame) -> tuple:
    """Count and order-free digests: equal for equal edge sets."""
    row = e.agg(F.count("*"), F.bit_xor(F.xxhash64("hi", "lo")), F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)"))).first()
    return tuple(row)
