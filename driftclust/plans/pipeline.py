"""The whole method over DataFrames: one data set, chunks, or a model for scoring.

Chunks are shuffled by chunk_id and each is clustered in one task, as training is
sequential, whatever its size: nothing here cuts it. ``cluster_sharded``, which
the caller has to choose, cuts a set into shards that are trained apart; their
maps are united (the map is a union of independent subnets by definition), and
further passes add up the cells' statistics. ``max_rows_per_task`` is a limit of
the streaming path, which refuses a larger chunk.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators import baselines, growing_map, map_frames, merging
from ..operators.growing_map import GrowingMap
from ..params import Params

TRACE = "chunk_id long, k int, a int, b int, log_theta double, omega double"
NEURONS = "chunk_id long, neuron int, subnet int, cluster int, w array<double>, strain double, hits long"
EDGES = "chunk_id long, a int, b int"
#: Tasks that share the search for the neighbours of one chunk.
NEAR_SHARES = 8
COUNTERS = "chunk_id long, n long, q int, subnets int, k_hat int, steps long, splits long, joins long, distances long, gaps long"


@dataclass
class Fitted:
    """What clustering one chunk in memory gives."""

    labels: np.ndarray
    map: GrowingMap
    cell: np.ndarray
    trace: merging.Trace
    groups: np.ndarray
    k: int


def fit_chunk(x: np.ndarray, p: Params, state: GrowingMap | None = None, near: np.ndarray | None = None) -> Fitted:
    """The method on the rows of x: map, cells, merging, choice of k. near: their
    neighbours where they are known, s at least."""
    return fit_cells(x, growing_map.fit(x, p, state), p, near)


def fit_cells(x: np.ndarray, m: GrowingMap, p: Params, near: np.ndarray | None = None) -> Fitted:
    """What follows on a trained map: cells, merging, choice of k."""
    cell, _ = growing_map.nearest(x, m.w)
    cells = merging.cell_stats(x, cell, m.q)
    if p.separability == "object":
        near = merging.neighbours(x, p.s) if near is None else merging.fewer(x, near, p.s)
        cross, s = merging.cross_pairs(near, cell, m.q), max(near.shape[1], 1)
    else:
        cross, s = merging.neuron_cross(m.w, p.s), min(p.s, max(m.q - 1, 1))
    return choose(m, cell, cells, cross, s, p)


def choose(m: GrowingMap, cell: np.ndarray, cells: merging.Cells, cross, s: int, p: Params) -> Fitted:
    if p.schedule == "none":
        groups = np.where(cells.n > 0, np.arange(m.q), -1)
        k = int((cells.n > 0).sum())
        t = merging.Trace([k], [-1], [-1], [float("nan")], [merging.separability(cross, np.arange(m.q), s)], groups)
        return Fitted(groups[cell], m, cell, t, groups, k)
    t = merging.run(cells, m.subnet, m.edges(), cross, s, p)
    k = p.k or merging.best_k(np.array(t.k), np.array(t.log_theta), np.array(t.omega), p.rule, p.min_k, p.theta, p.max_k)
    groups = t.groups(k)
    return Fitted(groups[cell], m, cell, t, groups, k)


def _flat(column) -> np.ndarray:
    """The values of an Arrow column of lists, one list after the other."""
    return column.combine_chunks().flatten().to_numpy(zero_copy_only=False)


def _matrix(part: pd.DataFrame) -> np.ndarray:
    return np.array(part["x"].to_list(), float).reshape(len(part), -1)


def _ordered(part: pd.DataFrame) -> pd.DataFrame:
    """Rows in an order that no shuffle changes; training permutes from it."""
    return part.sort_values("obj_id", kind="stable").reset_index(drop=True)


def _sorted(part: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """(obj_id, x) of an Arrow table in the order of ``_ordered``, values side by side."""
    ids = part["obj_id"].to_numpy()
    order = np.argsort(ids, kind="stable")
    return ids[order], _flat(part["x"]).reshape(len(ids), -1)[order]


LABELS = "chunk_id long, obj_id long, cluster int"


def _labelled(chunk, ids: np.ndarray, labels) -> pa.Table:
    return pa.table({"chunk_id": pa.repeat(chunk.cast(pa.int64()), len(ids)), "obj_id": pa.array(ids, pa.int64()), "cluster": np.asarray(labels).astype(np.int32)})


def cluster_chunks(points: DataFrame, p: Params = Params()) -> DataFrame:
    """chunk_id, obj_id, cluster of every point; each chunk on its own (cold)."""

    def run(part: pa.Table) -> pa.Table:
        chunk, (ids, x) = part["chunk_id"][0], _sorted(part)
        del part
        return _labelled(chunk, ids, fit_chunk(x, p).labels)

    return points.select("chunk_id", "obj_id", "x").groupBy("chunk_id").applyInArrow(run, LABELS)


def keys_apart(n: int) -> list[int]:
    """For each of n partitions the least key that Spark's hash sends there, so that
    no two long tasks wait for each other in one partition."""
    low, found, key = 0xFFFFFFFF, {}, 0
    turn = lambda v, by: (v << by | v >> (32 - by)) & low
    while len(found) < n:
        h = 42 ^ (turn(key * 0xCC9E2D51 & low, 15) * 0x1B873593 & low)
        h = (turn(h, 13) * 5 + 0xE6546B64 & low) ^ 4
        h = (h ^ h >> 16) * 0x85EBCA6B & low
        h = (h ^ h >> 13) * 0xC2B2AE35 & low
        h ^= h >> 16
        found.setdefault((h - (1 << 32) if h >> 31 else h) % n, key)
        key += 1
    return [found[i] for i in range(n)]


def neighbour_lists(points: DataFrame, s: int) -> DataFrame:
    """chunk_id, places of some rows in the chunk's order and of their s neighbours
    (as 32-bit integers); several tasks share the rows of a chunk."""

    def find(part: pa.Table) -> pa.Table:
        share, chunk, x = part["share"][0].as_py(), part["chunk_id"][0].as_py(), _sorted(part)[1]
        rows = merging.share_of_rows(x, share, NEAR_SHARES)
        near = merging.neighbours(x, s, rows=rows) if len(rows) else np.zeros((0, 1), np.int64)
        step = 100_000
        cut = lambda v: [v[lo : lo + step].astype("<i4").tobytes() for lo in range(0, len(rows), step)]
        out = cut(rows)
        return pa.table({"chunk_id": pa.array([chunk] * len(out), pa.int64()), "row": pa.array(out, pa.binary()), "near": pa.array(cut(near), pa.binary())})

    keys = F.array(*map(F.lit, keys_apart(NEAR_SHARES)))
    shared = points.select("chunk_id", "obj_id", "x", F.posexplode(keys).alias("share", "key")).repartition(NEAR_SHARES, "key")
    return shared.groupBy("key", "chunk_id").applyInArrow(find, "chunk_id long, row binary, near binary")


def _held(lists: pa.Table, n: int) -> np.ndarray | None:
    """The rows of ``neighbour_lists`` of one chunk as one array."""
    held = None
    for row, found in zip(lists["row"], lists["near"], strict=True):
        rows = np.frombuffer(row.as_buffer(), "<i4")
        found = np.frombuffer(found.as_buffer(), "<i4").reshape(len(rows), -1)
        held = np.zeros((n, found.shape[1]), np.int32) if held is None else held
        held[rows] = found
    return held


def cluster_variants(points: DataFrame, variants: dict[str, Params]) -> DataFrame:
    """``cluster_chunks`` with each of some parameters: method, chunk_id, obj_id,
    cluster. Neighbours, the same for all, are found once; each variant of a chunk
    is a task."""
    near = neighbour_lists(points, max(p.s for p in variants.values()))

    def run(part: pa.Table, lists: pa.Table) -> pa.Table:
        method, chunk, (ids, x) = part["method"][0].as_py(), part["chunk_id"][0].as_py(), _sorted(part)
        del part
        held = _held(lists, len(x))
        del lists
        labels = fit_chunk(x, variants[method], near=held).labels.astype(np.int32)
        return pa.table({"method": pa.repeat(method, len(ids)), "chunk_id": pa.repeat(pa.scalar(chunk, pa.int64()), len(ids)), "obj_id": ids, "cluster": labels})

    each = F.explode(F.array(*[F.struct(F.lit(m).alias("method"), F.lit(k).alias("key")) for m, k in zip(variants, keys_apart(len(variants)), strict=True)])).alias("v")
    by = ["key", "chunk_id"]
    given, lists = (df.select(*columns, each).select(*columns, "v.*").repartition(len(variants), "key").groupBy(*by) for df, columns in ((points, ["chunk_id", "obj_id", "x"]), (near, ["chunk_id", "row", "near"])))
    return given.cogroup(lists).applyInArrow(run, "method string, chunk_id long, obj_id long, cluster int")


def cluster(points: DataFrame, p: Params = Params()) -> DataFrame:
    """All points as one data set; several tasks share the search for neighbours."""
    points = points.withColumn("chunk_id", F.lit(0).cast("long"))
    if p.separability != "object":
        return cluster_chunks(points, p)
    return cluster_variants(points, {"": p}).drop("method")


def cluster_in_order(points: DataFrame, p: Params = Params()) -> DataFrame:
    """Chunks in order with the map carried over (warm): one task a stream_key trains
    it and gives the map as each chunk left it, the rest is a task for each chunk."""
    if "stream_key" not in points.columns:
        points = points.withColumn("stream_key", F.lit("all"))

    by = ["stream_key", "chunk_id"]

    def train(part: pa.Table) -> pa.Table:
        chunk_ids, order = part["chunk_id"].to_numpy(), np.lexsort((part["obj_id"].to_numpy(), part["chunk_id"].to_numpy()))
        key, x = part["stream_key"][0], _flat(part["x"]).reshape(len(order), -1)
        del part
        state, out, won = None, [], {}
        for n, chunk in enumerate(np.split(order, 1 + np.flatnonzero(np.diff(chunk_ids[order])))):
            state = growing_map.fit(x[chunk], replace(p, prune="off"), state)
            out.append((int(chunk_ids[chunk[0]]), state.w.tobytes(), state.subnet.tobytes(), np.array(state.edges(), np.int64).tobytes()))
            if p.prune == "idle":
                for s in set(state.subnet.tolist()):
                    if int(state.hits[state.subnet == s].sum()) >= p.min_hits:
                        won[s] = n
                gone = np.array([n - won.get(int(s), n) >= p.idle_chunks for s in state.subnet])
                if gone.any() and not gone.all():
                    state.drop(gone)
        ids, *arrays = zip(*out, strict=True)
        return pa.table({"stream_key": pa.repeat(key, len(out)), "chunk_id": pa.array(ids, pa.int64()), **{c: pa.array(v, pa.binary()) for c, v in zip(("w", "subnet", "edges"), arrays, strict=True)}})

    def run(part: pa.Table, held: pa.Table) -> pa.Table:
        key, chunk, (ids, x) = part["stream_key"][0], part["chunk_id"][0], _sorted(part)
        w, subnet, edges = (np.frombuffer(held[c][0].as_buffer(), t) for c, t in (("w", float), ("subnet", np.int64), ("edges", np.int64)))
        m = GrowingMap(w.reshape(-1, x.shape[1]), np.zeros(len(subnet)), subnet, np.zeros(len(subnet), np.int64), [set() for _ in subnet])
        for a, b in edges.reshape(-1, 2).tolist():
            m.link(a, b)
        labels = fit_cells(x, m, p).labels.astype(np.int32)
        return pa.table({"stream_key": pa.repeat(key, len(ids)), "chunk_id": pa.repeat(chunk, len(ids)), "obj_id": ids, "cluster": labels})

    points = points.select("stream_key", "chunk_id", "obj_id", "x")
    maps = points.groupBy("stream_key").applyInArrow(train, "stream_key string, chunk_id long, w binary, subnet binary, edges binary")
    return points.groupBy(*by).cogroup(maps.groupBy(*by)).applyInArrow(run, "stream_key string, chunk_id long, obj_id long, cluster int")


def _per_chunk(points: DataFrame, p: Params, schema: str, rows) -> DataFrame:
    def run(part: pd.DataFrame) -> pd.DataFrame:
        part = _ordered(part)
        return pd.DataFrame(rows(int(part["chunk_id"].iloc[0]), len(part), fit_chunk(_matrix(part), p)), columns=[c.split()[0] for c in schema.split(", ")])

    return points.select("chunk_id", "obj_id", "x").groupBy("chunk_id").applyInPandas(run, schema)


def trace(points: DataFrame, p: Params = Params()) -> DataFrame:
    """The merge trace of each chunk."""
    return _per_chunk(points, p, TRACE, lambda c, n, f: [(c, *r) for r in zip(f.trace.k, f.trace.a, f.trace.b, f.trace.log_theta, f.trace.omega, strict=True)])


def neurons(points: DataFrame, p: Params = Params()) -> DataFrame:
    """Neurons of each chunk's map, with the cluster that they ended in."""
    return _per_chunk(points, p, NEURONS, lambda c, n, f: [(c, i, int(f.map.subnet[i]), int(f.groups[i]), f.map.w[i].tolist(), float(f.map.strain[i]), int(f.map.hits[i])) for i in range(f.map.q)])


def edges(points: DataFrame, p: Params = Params()) -> DataFrame:
    return _per_chunk(points, p, EDGES, lambda c, n, f: [(c, a, b) for a, b in f.map.edges()])


def counters(points: DataFrame, p: Params = Params()) -> DataFrame:
    """Counted operations as rows: retried tasks don't count twice."""
    return _per_chunk(points, p, COUNTERS, lambda c, n, f: [(c, n, f.map.q, len(set(f.map.subnet.tolist())), f.k, f.map.steps, f.map.splits, f.map.joins, f.map.distances, f.trace.gaps)])


def predict(points: DataFrame, model: DataFrame) -> DataFrame:
    """Clusters of new points under a fitted map (rows of ``neurons``); neurons
    that no training point chose don't take part."""
    live = model.where("cluster >= 0").persist()  # read twice; fitting is the long part
    won = map_frames.winners(points, live.select("neuron", "w"))
    return won.join(F.broadcast(live.select("neuron", "cluster")), "neuron").drop("neuron", "dist")


def cluster_sharded(points: DataFrame, p: Params = Params(), shards: int = 8) -> DataFrame:
    """One data set of any size. Shards are trained apart, their maps united and
    written to neurons; winners and the cells' sums are one pass each, the
    objects' neighbours are found block by block; merging sees cells only."""
    rows = points.select("obj_id", "x").withColumn("shard", F.pmod(F.xxhash64("obj_id"), F.lit(shards)).cast("int"))
    d = len(rows.first()["x"])

    def train(part: pd.DataFrame) -> pd.DataFrame:
        part = _ordered(part)
        m = growing_map.fit(_matrix(part), replace(p, subnets=max(1, -(-p.subnets // 2))))
        shard = int(part["shard"].iloc[0])
        out = [(shard, i, int(m.subnet[i]), m.w[i].tolist(), -1, -1) for i in range(m.q)]
        return pd.DataFrame(out + [(shard, -1, -1, [], a, b) for a, b in m.edges()], columns=["shard", "neuron", "subnet", "w", "a", "b"])

    got = rows.groupBy("shard").applyInPandas(train, "shard int, neuron int, subnet int, w array<double>, a int, b int").orderBy("shard", "neuron").toArrow()
    shard, neuron, subnet = (got[c].to_numpy() for c in ("shard", "neuron", "subnet"))
    own = neuron >= 0
    base = np.zeros(int(shard.max()) + 2, np.int64)  # of each shard its first neuron's number
    base[1:] = np.cumsum(np.bincount(shard[own], minlength=len(base) - 1))
    names = np.unique(np.column_stack([shard[own], subnet[own]]), axis=0, return_inverse=True)[1].reshape(-1)
    m = GrowingMap(_flat(got.filter(pa.array(own))["w"]).reshape(-1, d), np.zeros(int(own.sum())), names, np.zeros(int(own.sum()), np.int64), [set() for _ in range(int(own.sum()))])
    for a, b in zip(*((base[shard[~own]] + got[c].to_numpy()[~own]).tolist() for c in "ab"), strict=True):
        m.link(a, b)
    book = points.sparkSession.createDataFrame([(i, w.tolist()) for i, w in enumerate(m.w)], "neuron long, w array<double>")
    won = map_frames.winners(points.select("obj_id", "x"), book)
    sums = map_frames.cell_sums(won, ["neuron"], d).toArrow()
    at = sums["neuron"].to_numpy()
    cells = merging.Cells(np.zeros(m.q), np.zeros((m.q, d)), np.zeros((m.q, d, d)))
    cells.n[at], cells.s1[at] = sums["n"].to_numpy(), _flat(sums["s1"]).reshape(-1, d)
    for (i, j), v in zip(np.transpose(np.triu_indices(d)), _flat(sums["s2"]).reshape(len(at), -1).T, strict=True):
        cells.s2[at, i, j] = cells.s2[at, j, i] = v
    if p.separability == "object":
        # As pairs with a count: a table of all pairs of cells outgrows the driver.
        near = map_frames.knn(points, p.s, shards)
        pairs = map_frames.cross_counts(near, won.select("obj_id", F.col("neuron").alias("cell"))).toArrow()
        cross, s = (pairs["cell_a"].to_numpy(), pairs["cell_b"].to_numpy(), pairs["c"].to_numpy().astype(float)), p.s
    else:
        cross, s = merging.neuron_cross(m.w, p.s), min(p.s, m.q - 1)
    f = choose(m, np.zeros(0, np.int64), cells, cross, s, p)
    to = points.sparkSession.createDataFrame([(i, int(g)) for i, g in enumerate(f.groups)], "neuron long, cluster int")
    return won.join(F.broadcast(to), "neuron").select("obj_id", "cluster")


def batch_codebook(points: DataFrame, start: DataFrame, rounds: int = 5, grow: int = 2) -> DataFrame:
    """Order-free training for data of any size: every round is one pass whose
    shuffle holds a sum for each neuron and task; the most strained split."""
    d = len(start.first()["w"])

    def sums_of(w: np.ndarray):
        book = points.sparkSession.createDataFrame([(i, v.tolist()) for i, v in enumerate(w)], "neuron long, w array<double>")
        n, total, strain = np.zeros(len(w)), np.zeros((len(w), d)), np.zeros(len(w))
        x = [F.sum(F.element_at("x", i + 1)).alias(f"s{i}") for i in range(d)]
        for r in map_frames.winners(points.select("obj_id", "x"), book).groupBy("neuron").agg(F.count("*").alias("n"), F.sum("dist").alias("t"), *x).collect():
            n[r.neuron], strain[r.neuron], total[r.neuron] = r.n, r.t, [r[f"s{i}"] for i in range(d)]
        return n, total, strain

    w = growing_map.batch_fit(sums_of, np.array([r.w for r in start.orderBy("neuron").collect()], float), rounds, grow)
    return points.sparkSession.createDataFrame([(i, v.tolist()) for i, v in enumerate(w)], "neuron long, w array<double>")


def baseline_labels(x: np.ndarray, method: str, k: int, seed: int) -> np.ndarray:
    return baselines.METHODS[method][0](x, min(k, len(x)), seed) if len(x) > 3 else np.zeros(len(x), int)


def seconds_of(points: DataFrame, runs: list[tuple[str, int]], k: int, p: Params = Params()) -> dict[tuple[str, int], tuple[int, float]]:
    """(method, share) -> (n, CPU seconds) of one method on the points whose column
    ``part`` is below the share, as one set. The runs are tasks of one job, the
    first ones first, and each takes its own time."""

    def run(part: pa.Table) -> pa.Table:
        method, share, x = part["method"][0].as_py(), part["share"][0].as_py(), _sorted(part)[1]
        del part
        t = time.process_time()
        if method == "growing_map":
            fit_chunk(x, p)
        else:
            baseline_labels(x, method, k if baselines.METHODS[method][1] else 0, p.seed)
        return pa.table({"method": [method], "share": pa.array([share], pa.int32()), "n": [len(x)], "seconds": [time.process_time() - t]})

    each = [F.struct(F.lit(m).alias("method"), F.lit(share).alias("share"), F.lit(key).alias("key")) for (m, share), key in zip(runs, keys_apart(len(runs)), strict=True)]
    rows = points.select("obj_id", "x", "part", F.explode(F.array(*each)).alias("v")).where("part < v.share").select("obj_id", "x", "v.*")
    got = rows.repartition(len(runs), "key").groupBy("key").applyInArrow(run, "method string, share int, n long, seconds double").collect()
    return {(m, share): (0, 0.0) for m, share in runs} | {(r.method, r.share): (r.n, r.seconds) for r in got}


def baseline(points: DataFrame, method: str, k: int = 0, seed: int = 1, shared: bool = False) -> DataFrame:
    """A comparison algorithm on each chunk, as if it were a static set. shared: where
    it starts from neighbours, several tasks look for those of a chunk."""

    def run(part: pa.Table, lists: pa.Table | None = None) -> pa.Table:
        chunk, (ids, x) = part["chunk_id"][0], _sorted(part)
        del part
        near = None if lists is None else _held(lists, len(x))
        if near is None or len(x) <= 3:
            return _labelled(chunk, ids, baseline_labels(x, method, k, seed))
        return _labelled(chunk, ids, baselines.METHODS[method][0](x, min(k, len(x)), seed, near=near))

    rows = points.select("chunk_id", "obj_id", "x")
    if shared and method in baselines.FROM_NEIGHBOURS:
        lists = neighbour_lists(points, baselines.FROM_NEIGHBOURS[method])
        return rows.groupBy("chunk_id").cogroup(lists.groupBy("chunk_id")).applyInArrow(lambda part, found: run(part, found), LABELS)
    return rows.groupBy("chunk_id").applyInArrow(lambda part: run(part), LABELS)


def with_truth(points: DataFrame, clusters: DataFrame) -> DataFrame:
    return points.join(clusters, ["chunk_id", "obj_id"])


def last_version(chunks: DataFrame, versions: DataFrame) -> DataFrame:
    """As-of join: the newest map version at or before each chunk's time t."""
    both = chunks.select("t", F.lit(None).cast("long").alias("version")).unionByName(versions.select("t", "version"))
    seen = F.last("version", ignorenulls=True).over(Window.orderBy("t", F.col("version").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, Window.currentRow))
    return both.withColumn("as_of", seen).where("version is null").select("t", "as_of")
