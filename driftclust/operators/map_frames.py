"""Map, gap and separability operators over DataFrames.

A codebook (neuron, w, ...) is small. ``winners`` checks its size before the
broadcast and raises an error beyond ``CODEBOOK_ROWS``; the forms for SQL users
broadcast what they are given.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import growing_map, merging
from .features import dist, sq_dist

#: Neurons beyond which ``winners`` raises an error.
CODEBOOK_ROWS = 100_000
#: Axes up to which boxes find neighbours; with more, all pairs are compared.
BOX_AXES = 8


def winners_sql(points: DataFrame, codebook: DataFrame) -> DataFrame:
    """obj_id, neuron, d2: the nearest neuron, ties to the lowest number; as a
    broadcast join with a minimum, fit for SQL users and small codebooks."""
    pairs = points.crossJoin(F.broadcast(codebook.select("neuron", "w")))
    best = F.min(F.struct(sq_dist(F.col("x"), F.col("w")).alias("d2"), "neuron"))
    return pairs.groupBy("obj_id").agg(best.alias("b")).select("obj_id", "b.neuron", "b.d2")


def winners(points: DataFrame, codebook: DataFrame) -> DataFrame:
    """``points`` with neuron and dist, by blocks in NumPy against the broadcast
    codebook; distances are never kept."""
    rows = codebook.select("neuron", "w").orderBy("neuron").limit(CODEBOOK_ROWS + 1).collect()
    if len(rows) > CODEBOOK_ROWS:
        raise ValueError("the codebook is too large to broadcast: search it by subnet")
    ids, w = np.array([r.neuron for r in rows]), np.array([r.w for r in rows], float)
    held = points.sparkSession.sparkContext.broadcast((ids, w))

    def find(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        ids, w = held.value
        for part in parts:
            if len(part):
                win, d = growing_map.nearest(np.stack(part["x"].to_list()), w)
                yield part.assign(neuron=ids[win], dist=d)

    kinds = ", ".join(f"`{n}` {t}" for n, t in points.dtypes)
    return points.mapInPandas(find, f"{kinds}, neuron long, dist double")


def cell_sums(assigned: DataFrame, by: list[str], d: int) -> DataFrame:
    """n, s1 (sums) and s2 (upper triangle of the sums of products) by cell; one
    pass, added up on the map side."""
    x = lambda i: F.element_at("x", i + 1)
    first = [F.sum(x(i)).alias(f"s1_{i}") for i in range(d)]
    second = [F.sum(x(i) * x(j)).alias(f"s2_{i}_{j}") for i in range(d) for j in range(i, d)]
    out = assigned.groupBy(*by).agg(F.count("*").alias("n"), *first, *second)
    return out.select(*by, "n", F.array(*[f"s1_{i}" for i in range(d)]).alias("s1"), F.array(*[f"s2_{i}_{j}" for i in range(d) for j in range(i, d)]).alias("s2"))


def project_pair(points: DataFrame, a: Column, b: Column) -> DataFrame:
    """u: place of each point on the line through two centres, at 0.5 and -0.5."""
    w = F.zip_with(a, b, lambda p, q: p - q)
    mid = F.zip_with(a, b, lambda p, q: (p + q) / 2)
    dot = F.aggregate(F.zip_with(F.zip_with("x", mid, lambda v, m: v - m), w, lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)
    return points.withColumn("u", dot / F.aggregate(w, F.lit(0.0), lambda s, v: s + v * v))


def mixture_curve(pairs: DataFrame) -> DataFrame:
    """A row for each of the 101 places u with the mixture density m; pairs has
    pair, n_i, v_i, n_j, v_j."""
    u = pairs.withColumn("step", F.explode(F.sequence(F.lit(-50), F.lit(50)))).withColumn("u", F.col("step") / 100.0)
    part = lambda n, v, c: F.col(n) / (F.col("n_i") + F.col("n_j")) * F.exp(-0.5 * F.pow(F.col("u") - c, 2) / F.col(v)) / F.sqrt(F.lit(6.283185307179586) * F.col(v))
    return u.withColumn("m", part("n_i", "v_i", F.lit(0.5)) + part("n_j", "v_j", F.lit(-0.5))).select("pair", "step", "u", "m")


def log_gaps(pairs: DataFrame) -> DataFrame:
    """pair, log_gap: minus the log of the least mixture density."""
    return mixture_curve(pairs).groupBy("pair").agg((-F.ln(F.min("m"))).alias("log_gap"))


def cluster_pairs(points: DataFrame, cluster: str = "label") -> DataFrame:
    """pair, i, j, n_i, v_i, n_j, v_j for all pairs of clusters: one-dimensional
    variances on the line through the two centres."""
    from .features import by_position

    c = by_position(points.withColumn("cluster", F.col(cluster)), ["cluster"], ("avg", "centre"))
    l, r = c.alias("l"), c.alias("r")  # noqa: E741
    lines = l.join(r, F.col("l.cluster") < F.col("r.cluster")).select(F.col("l.cluster").alias("i"), F.col("r.cluster").alias("j"), F.col("l.centre").alias("ci"), F.col("r.centre").alias("cj"))
    members = points.withColumn("cluster", F.col(cluster)).join(F.broadcast(lines), (F.col("cluster") == F.col("i")) | (F.col("cluster") == F.col("j")))
    u = project_pair(members, F.col("ci"), F.col("cj"))
    mine = lambda side, f, c: f(F.when(F.col("cluster") == F.col(side), c))
    out = u.groupBy("i", "j").agg(mine("i", F.count, F.lit(1)).alias("n_i"), F.greatest(mine("i", F.var_pop, F.col("u")), F.lit(1e-6)).alias("v_i"), mine("j", F.count, F.lit(1)).alias("n_j"), F.greatest(mine("j", F.var_pop, F.col("u")), F.lit(1e-6)).alias("v_j"))
    return out.withColumn("pair", F.concat_ws("-", "i", "j"))


def classes(points: DataFrame) -> DataFrame:
    """obj_id, x with those of equal x: their lowest id (``cls``), number
    (``size``) and the row's place among them (``nth``, from 1)."""
    same = Window.partitionBy("x")
    return points.select("obj_id", "x", F.min("obj_id").over(same).alias("cls"), F.count("*").over(same).alias("size"), F.row_number().over(same.orderBy("obj_id")).alias("nth"))


def _matrix(table: pa.Table) -> np.ndarray:
    x = table.column("x").combine_chunks()
    return x.flatten().to_numpy(zero_copy_only=False).reshape(len(x), -1)


def by_blocks(left: DataFrame, right: DataFrame, blocks: int, compare, schema: str) -> DataFrame:
    """``compare`` (two Arrow tables to one) on each pair of blocks of left and
    right; a task holds one pair. Both have cls, by whose hash blocks are dealt."""
    block = F.pmod(F.xxhash64("cls"), F.lit(blocks)).cast("int")
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    a = left.withColumn("p", block).withColumn("q", every)
    renamed = right.select(*[F.col(c).alias(c) for c in right.columns])  # columns of its own, where both are one frame
    b = renamed.withColumn("q", block).withColumn("p", every)
    return a.groupBy("p", "q").cogroup(b.groupBy("p", "q")).applyInArrow(compare, schema)


def knn(points: DataFrame, s: int, blocks: int = 8) -> DataFrame:
    """obj_id, nbr_id, rank of the s nearest others, ties to the lower id.

    Distinct x are compared once, in NumPy and block against block; of equal x the
    s + 1 lowest ids can be neighbours, so copies never become pairs.
    """
    rows = classes(points)

    def nearest_of(left: pa.Table, right: pa.Table) -> pa.Table:
        out = []
        if len(left) and len(right):
            right = right.sort_by("obj_id")
            mine, ids = left.column("cls").to_numpy(), right.column("obj_id").to_numpy()
            x, y = _matrix(left), _matrix(right)
            if x.shape[1] <= BOX_AXES:
                found, d2 = merging.nearest_in(x, y, ids, min(s + 1, len(ids)))
                return pa.table({"cls": np.repeat(mine, found.shape[1]), "nbr_id": found.reshape(-1), "d2": d2.reshape(-1)})
            for lo, close in merging.close_pairs(x, y, min(s + 1, len(ids))):
                r, c, d2 = close
                keep = merging.first_of_each(r, d2, c, s + 1)
                out.append(pa.table({"cls": mine[lo + r[keep]], "nbr_id": ids[c[keep]], "d2": d2[keep]}))
        return pa.concat_tables(out) if out else pa.table({"cls": pa.array([], pa.int64()), "nbr_id": pa.array([], pa.int64()), "d2": pa.array([], pa.float64())})

    near = by_blocks(rows.where("nth = 1").select("cls", "x"), rows.where(F.col("nth") <= s + 1).select("obj_id", "cls", "x"), blocks, nearest_of, "cls long, nbr_id long, d2 double")
    few = near.withColumn("r", F.row_number().over(Window.partitionBy("cls").orderBy("d2", "nbr_id"))).where(F.col("r") <= s + 1)
    mine = rows.select("obj_id", "cls").join(few, "cls").where("obj_id <> nbr_id")
    return mine.withColumn("rank", F.row_number().over(Window.partitionBy("obj_id").orderBy("r"))).where(F.col("rank") <= s).select("obj_id", "nbr_id", "rank")


#: The name by which ``cluster_sharded``'s users know it.
knn_blocks = knn


def within(points: DataFrame, d2: float, blocks: int = 8) -> DataFrame:
    """obj_id, rho: the number of others whose squared distance is below d2."""
    rows = classes(points)

    def count(left: pa.Table, right: pa.Table) -> pa.Table:
        n = np.zeros(len(left), np.int64)
        if len(left) and len(right):
            size = right.column("size").to_numpy()
            for lo, inside in merging.pairs_below(_matrix(left), _matrix(right), d2):
                n[lo : lo + len(inside)] = inside @ size
        return pa.table({"cls": left.column("cls"), "n": n})

    reps = rows.where("nth = 1").select("cls", "x", "size")
    rho = by_blocks(reps, reps, blocks, count, "cls long, n long").groupBy("cls").agg((F.sum("n") - (1 if d2 > 0 else 0)).alias("rho"))
    return rows.select("obj_id", "cls").join(rho, "cls").select("obj_id", "rho")


def nearest_denser(points: DataFrame, rho: DataFrame, blocks: int = 8) -> DataFrame:
    """obj_id, parent, d2: the nearest of those with a larger rho, or an equal one
    and a lower id; ties to the lower id. rho (obj_id, rho) is equal for equal x,
    so a copy follows the lowest id of its class."""
    rows = classes(points)

    def find(left: pa.Table, right: pa.Table) -> pa.Table:
        out = []
        if len(left) and len(right):
            right = right.sort_by("cls")
            mine, ids = left.column("cls").to_numpy(), right.column("cls").to_numpy()
            lr, rr = left.column("rho").to_numpy(), right.column("rho").to_numpy()
            x, y = _matrix(left), _matrix(right)
            allowed = lambda lo, hi: (rr[None, :] > lr[lo:hi, None]) | ((rr[None, :] == lr[lo:hi, None]) & (ids[None, :] < mine[lo:hi, None]))
            for lo, close in merging.close_pairs(x, y, 1, allowed):
                r, c, d2 = close
                keep = merging.first_of_each(r, d2, c, 1)
                out.append(pa.table({"cls": mine[lo + r[keep]], "parent": ids[c[keep]], "d2": d2[keep]}))
        return pa.concat_tables(out) if out else pa.table({"cls": pa.array([], pa.int64()), "parent": pa.array([], pa.int64()), "d2": pa.array([], pa.float64())})

    reps = rows.where("nth = 1").select("obj_id", "cls", "x").join(rho, "obj_id").select("cls", "x", "rho")
    best = by_blocks(reps, reps, blocks, find, "cls long, parent long, d2 double").groupBy("cls").agg(F.min(F.struct("d2", "parent")).alias("b"))
    copies = rows.where("nth > 1").select("obj_id", F.col("cls").alias("parent"), F.lit(0.0).alias("d2"))
    return best.select(F.col("cls").alias("obj_id"), "b.parent", "b.d2").unionByName(copies)


def cross_counts(near: DataFrame, cells: DataFrame) -> DataFrame:
    """cell_a, cell_b, c: neighbours from one cell to another."""
    a = cells.select(F.col("obj_id"), F.col("cell").alias("cell_a"))
    b = cells.select(F.col("obj_id").alias("nbr_id"), F.col("cell").alias("cell_b"))
    return near.join(a, "obj_id").join(b, "nbr_id").groupBy("cell_a", "cell_b").agg(F.count("*").alias("c"))


def omega(cross: DataFrame, s: int) -> DataFrame:
    """Worst cluster's foreign neighbours over s, from counts between clusters."""
    return cross.groupBy("cell_a").agg(F.sum(F.when(F.col("cell_a") != F.col("cell_b"), F.col("c")).otherwise(0)).alias("foreign")).agg((F.max("foreign") / F.lit(float(s))).alias("omega"))


def spreads(codebook: DataFrame, edges: DataFrame) -> DataFrame:
    """Mean edge length at each neuron."""
    both = edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    l, r = codebook.select(F.col("neuron").alias("a"), F.col("w").alias("wa")), codebook.select(F.col("neuron").alias("b"), F.col("w").alias("wb"))
    return both.join(F.broadcast(l), "a").join(F.broadcast(r), "b").groupBy(F.col("a").alias("neuron")).agg(F.avg(dist(F.col("wa"), F.col("wb"))).alias("spread"))


def strained_pair(codebook: DataFrame) -> DataFrame:
    """v, g: the most strained neuron and the most strained of another subnet."""
    top = codebook.orderBy(F.desc("strain"), "neuron").limit(1).select(F.col("neuron").alias("v"), F.col("subnet").alias("vs"))
    other = codebook.join(F.broadcast(top), F.col("subnet") != F.col("vs")).groupBy("v").agg(F.max_by("neuron", F.struct("strain", -F.col("neuron"))).alias("g"))
    return top.select("v").join(other, "v", "left")


def split_test(codebook: DataFrame, edges: DataFrame) -> DataFrame:
    """v, g, q, split: whether the strained pair is further apart than v from its
    furthest neighbour q."""
    c = codebook.select("neuron", "w")
    pair = strained_pair(codebook)
    both = edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    at = lambda k, n: c.select(F.col("neuron").alias(k), F.col("w").alias(n))
    far = pair.join(at("v", "wv"), "v").join(both.withColumnRenamed("a", "v"), "v").join(at("b", "wb"), "b")
    far = far.withColumn("dq", dist(F.col("wv"), F.col("wb"))).groupBy("v").agg(F.max_by("b", F.struct("dq", -F.col("b"))).alias("q"), F.max("dq").alias("dq"))
    gap = pair.join(at("v", "wv"), "v").join(at("g", "wg"), "g").select("v", "g", dist(F.col("wv"), F.col("wg")).alias("dg"))
    return gap.join(far, "v").select("v", "g", "q", (F.col("dg") > F.col("dq")).alias("split"))


def kmeans_rounds(points: DataFrame, centres: DataFrame, rounds: int) -> DataFrame:
    """cluster, centre after some rounds; each is one pass with sums of a vector
    for each cluster and task in the shuffle."""
    from .features import by_position

    for _ in range(rounds):
        won = winners_sql(points, centres.select(F.col("cluster").alias("neuron"), F.col("centre").alias("w")))
        joined = points.join(won, "obj_id").withColumnRenamed("neuron", "cluster")
        centres = by_position(joined, ["cluster"], ("avg", "centre"))
    return centres


def som_round(points: DataFrame, codebook: DataFrame, radius: float, cols: int) -> DataFrame:
    """One batch round of a fixed grid: neighbourhood-weighted means."""
    from .features import by_position

    won = points.join(winners_sql(points, codebook), "obj_id")
    sums = by_position(won, ["neuron"], ("sum", "s")).join(won.groupBy("neuron").agg(F.count("*").alias("n")), "neuron").withColumnRenamed("neuron", "m")
    row, col = lambda c: F.floor(F.col(c) / cols), lambda c: F.col(c) % cols
    pairs = codebook.select("neuron").crossJoin(F.broadcast(sums))
    h = F.exp(-(F.pow(row("neuron") - row("m"), 2) + F.pow(col("neuron") - col("m"), 2)) / (2 * radius * radius))
    flat = pairs.withColumn("h", h).select("neuron", "h", "n", F.posexplode("s").alias("pos", "v"))
    return flat.groupBy("neuron", "pos").agg((F.sum(F.col("h") * F.col("v")) / F.sum(F.col("h") * F.col("n"))).alias("w"))
