"""Accuracy and cost measures as DataFrame plans.

``a`` has chunk columns ``by``, label and cluster for each object; geometry
measures also need x. Sums over pairs are taken in doubles: counts of pairs
outgrow a long.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import merging
from .features import by_position, dist

#: Tasks that share the comparisons of one group's clusters.
DBI_SHARES = 8


def contingency(a: DataFrame, by: list[str] | None = None) -> DataFrame:
    return a.groupBy(*(by or []), "label", "cluster").agg(F.count("*").alias("n"))


def _pairs(c: Column) -> Column:
    return c.cast("double") * (c - 1) / 2


def _grouped(df: DataFrame, by: list[str]):
    return df.groupBy(*by) if by else df.groupBy()


def _join(left: DataFrame, right: DataFrame, by: list[str]) -> DataFrame:
    return left.join(right, by) if by else left.crossJoin(F.broadcast(right))


def ari(a: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Adjusted Rand index; 1 where chance agreement is all there is."""
    by = by or []
    c = contingency(a, by)
    cells = _grouped(c, by).agg(F.sum(_pairs(F.col("n"))).alias("cells"), F.sum("n").alias("total"))
    rows = _grouped(c.groupBy(*by, "label").agg(F.sum("n").alias("m")), by).agg(F.sum(_pairs(F.col("m"))).alias("rows"))
    cols = _grouped(c.groupBy(*by, "cluster").agg(F.sum("n").alias("m")), by).agg(F.sum(_pairs(F.col("m"))).alias("cols"))
    e = F.col("rows") * F.col("cols") / _pairs(F.col("total"))
    top = (F.col("rows") + F.col("cols")) / 2
    value = F.when((_pairs(F.col("total")) == 0) | (top == e), F.lit(1.0)).otherwise((F.col("cells") - e) / (top - e))
    return _join(_join(cells, rows, by), cols, by).select(*by, value.alias("ari"))


def nmi(a: DataFrame, by: list[str] | None = None, norm: str = "arith") -> DataFrame:
    """Normalised mutual information; norm: arith, sqrt, min or max of the entropies."""
    by = by or []
    c = contingency(a, by)
    c = c.withColumn("a", F.sum("n").over(Window.partitionBy(*by, "label"))).withColumn("b", F.sum("n").over(Window.partitionBy(*by, "cluster")))
    c = _join(c, _grouped(contingency(a, by), by).agg(F.sum("n").alias("t")), by)
    info = F.sum(F.col("n") / F.col("t") * F.ln(F.col("n") * F.col("t") / (F.col("a").cast("double") * F.col("b"))))
    hl = F.sum(-F.col("n") / F.col("t") * F.ln(F.col("a") / F.col("t")))
    hc = F.sum(-F.col("n") / F.col("t") * F.ln(F.col("b") / F.col("t")))
    x = _grouped(c, by).agg(info.alias("i"), hl.alias("hl"), hc.alias("hc"))
    below = {"arith": (F.col("hl") + F.col("hc")) / 2, "sqrt": F.sqrt(F.col("hl") * F.col("hc")), "min": F.least("hl", "hc"), "max": F.greatest("hl", "hc")}[norm]
    both = (F.abs("hl") < 1e-15) & (F.abs("hc") < 1e-15)
    return x.select(*by, F.when(both, F.lit(1.0)).when(F.abs(below) < 1e-15, F.lit(0.0)).otherwise(F.col("i") / below).alias("nmi"))


def centres(a: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Mean vector of each cluster."""
    return by_position(a, [*(by or []), "cluster"], ("avg", "centre"))


def dbi(a: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Davies-Bouldin index; null for one cluster, coinciding centres skipped."""
    by = by or []
    c = centres(a, by)
    keys = [*by, "cluster"]
    spread = a.join(F.broadcast(c), keys).groupBy(*keys).agg(F.avg(dist(F.col("x"), F.col("centre"))).alias("s"))
    # Clusters alike in centre and spread are compared once; each task has all
    # centres of a group and looks for the worst of a share of them.
    alike = c.join(spread, keys).groupBy(*by, "centre", "s").agg(F.count("*").alias("m"))
    alike = alike.withColumn("own", F.pmod(F.xxhash64("centre", "s"), F.lit(DBI_SHARES)).cast("int")).withColumn("share", F.explode(F.sequence(F.lit(0), F.lit(DBI_SHARES - 1))))

    def compare(part: pd.DataFrame) -> pd.DataFrame:
        x, r, m = np.array(part["centre"].to_list(), float).reshape(len(part), -1), part["s"].to_numpy(), part["m"].to_numpy()
        mine = np.flatnonzero((part["own"] == part["share"]).to_numpy())
        total, n = 0.0, 0
        for rows in np.array_split(mine, max(1, len(mine) * len(x) // 2_000_000)):
            gap = np.sqrt(merging._sq(x[rows], x))
            worst = np.divide(r[rows][:, None] + r[None, :], gap, out=np.full(gap.shape, -1.0), where=gap > 0).max(axis=1, initial=-1.0)
            some = worst >= 0
            total, n = total + float((worst[some] * m[rows][some]).sum()), n + int(m[rows][some].sum())
        return part[by].head(1).assign(total=total, n=n) if by else pd.DataFrame({"total": [total], "n": [n]})

    kinds = ", ".join([*(f"`{c}` {t}" for c, t in alike.dtypes if c in by), "total double", "n long"])
    out = _grouped(alike.groupBy(*by, "share").applyInPandas(compare, kinds).where("n > 0"), by)
    return out.agg((F.sum("total") / F.sum("n")).alias("dbi"))


def ssq(a: DataFrame, by: list[str] | None = None, power: int = 1) -> DataFrame:
    """Sum of distances (power 1) or squared distances (2) to cluster centres."""
    by = by or []
    d = dist(F.col("x"), F.col("centre"))
    joined = a.join(F.broadcast(centres(a, by)), [*by, "cluster"])
    return _grouped(joined, by).agg(F.sum(d if power == 1 else F.pow(d, 2)).alias("ssq"))


def imbalance(a: DataFrame, by: list[str] | None = None, cluster: str = "cluster") -> DataFrame:
    """Largest over smallest cluster, and how many clusters there are."""
    n = a.groupBy(*(by or []), cluster).agg(F.count("*").alias("n"))
    return _grouped(n, by or []).agg((F.max("n") / F.min("n")).alias("ratio"), F.count("*").alias("k"))


def imbalance_series(a: DataFrame, chunk: str = "chunk_id", cluster: str = "cluster") -> DataFrame:
    """Ratio and k by chunk with their change from the chunk before."""
    w = Window.orderBy(chunk)
    s = imbalance(a, [chunk], cluster)
    return s.withColumn("d_ratio", F.col("ratio") - F.lag("ratio").over(w)).withColumn("d_k", F.col("k") - F.lag("k").over(w))


def k_error(a: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Clusters found less true clusters; whether everything fell into one."""
    g = _grouped(a, by or []).agg(F.count_distinct("cluster").alias("k_hat"), F.count_distinct("label").alias("k_true"))
    return g.withColumn("k_error", F.col("k_hat") - F.col("k_true")).withColumn("one_cluster", F.col("k_hat") == 1)


def minority_recall(a: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Share of the smallest true cluster that its best cluster holds."""
    by = by or []
    c = contingency(a, by)
    best = c.groupBy(*by, "label").agg(F.sum("n").alias("size"), F.max("n").alias("most"))
    return _grouped(best, by).agg(F.min_by(F.col("most") / F.col("size"), F.struct("size", "label")).alias("minority_recall"))


def summary(results: DataFrame) -> DataFrame:
    """Mean and sample deviation over chunks of stored result rows."""
    return results.groupBy("dataset", "method", "measure").agg(F.avg("value").alias("mean"), F.coalesce(F.stddev_samp("value"), F.lit(0.0)).alias("deviation"), F.count("value").alias("chunks"))


def rank_table(results: DataFrame, lower_better: tuple[str, ...] = ("dbi",)) -> DataFrame:
    """How often each method is first and second, by set and measure; nulls last."""
    mean = results.groupBy("dataset", "method", "measure").agg(F.avg("value").alias("mean"))
    signed = mean.withColumn("signed", F.when(F.col("measure").isin(*lower_better), F.col("mean")).otherwise(-F.col("mean")))
    w = Window.partitionBy("dataset", "measure").orderBy(F.col("signed").asc_nulls_last())
    placed = signed.where("mean is not null").withColumn("place", F.rank().over(w))
    return placed.groupBy("method").agg(F.count_if(F.col("place") == 1).alias("first"), F.count_if(F.col("place") == 2).alias("second"))


def predicted_costs(sizes: DataFrame, t: int = 15, rho: int = 100, s: int = 10, branching: int = 4) -> DataFrame:
    """Operation counts that the complexity analysis predicts; sizes: n, q, d."""
    n, q, d = F.col("n"), F.col("q"), F.col("d")
    b = F.lit(branching)
    return sizes.select(
        "n", "q", "d",
        (n * q).alias("winner_distances"),
        (n * (b + 1)).alias("pulls"),
        F.floor(n / rho).alias("structural_steps"),
        (n * q * q * b * d).alias("intra_merging"),
        (n * t * t * t * d).alias("inter_merging"),
        (n * n * q * d + n * q * s).alias("separability_objects"),
        (q * q * q * d + q * q * s).alias("separability_neurons"),
        (n * q * q * d).alias("total_time"),
        (n * d + n * q).alias("total_space"),
    )
