"""Quality: Bradley-Terry ranking learned from preference pairs of documents.

Every document has a vector of style measures and hashed word-shape shares. A
pair says that a document labelled 1 is preferred to one labelled 0; the score
difference is the pair's log-odds, so the loss is logistic in the difference of
the vectors. Every labelled row that isn't held out is trained on, and every pair
of such rows counts. Ranking leaves the score's origin free: the threshold is the
quantile of the training scores at the share of documents labelled 0, and the
published score is shifted so that it lies at ``cut`` there.

Null and empty texts score as their (all zero) measures say. Without both
classes all scores are 0.5. Repeated ids are scored each; extra columns are
ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import features
from .labelled import held_out, labelled
from .scratch import materialise, prepare


#: The grid of scores on which pairs are counted: places, their distance, and the
#: coarser one for the part of the curvature that a pair's rows share.
PLACES, STEP, CROSS = 4096, 1 / 32, 256
REACH = PLACES * STEP / 2


@dataclass(frozen=True)
class RankParams:
    #: Newton steps at most.
    rounds: int = 25
    l2: float = 1e-4
    cut: float = 0.3


@dataclass(frozen=True)
class RankModel:
    mean: np.ndarray
    scale: np.ndarray
    weight: np.ndarray
    shift: float

    def scores(self, x: np.ndarray) -> np.ndarray:
        s = ((x - self.mean) / self.scale) @ self.weight + self.shift
        return 1.0 / (1.0 + np.exp(-np.clip(s, -35, 35)))


def expand(x: np.ndarray) -> np.ndarray:
    """Measures with their squares, so that both extremes can count against a text."""
    return np.concatenate([x, x * x], axis=1)


def pair_tables(good: np.ndarray, bad: np.ndarray) -> tuple[float, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """From the numbers of rows at each place of the grid: mean loss of all pairs,
    then by place the sums of slope and curvature that a row of either class there
    has from the other class."""
    gap = np.arange(-PLACES + 1, PLACES) * STEP
    lose, total = 1.0 / (1.0 + np.exp(gap)), good.sum() * bad.sum()
    over = lambda other, f: np.convolve(other, f)[PLACES - 1 : 2 * PLACES - 1] / total
    bend = lose * (1 - lose)
    loss = float(good @ over(bad, np.logaddexp(0.0, -gap)))
    return loss, over(bad, lose), over(good, lose[::-1]), over(bad, bend), over(good, bend)


def _place(s: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Grid place at or below each score, and the share that goes to the next."""
    at = np.clip((s + REACH) / STEP, 0, PLACES - 1.001)
    lo = at.astype(np.int64)
    return lo, at - lo


def _sums(rows: DataFrame, of) -> list[np.ndarray]:
    """Sums over all rows of the arrays that ``of(x, y)`` gives for a batch; each
    task adds its own up."""

    def add(batches):
        total = None
        for batch in batches:
            if batch.num_rows:
                x = _expanded(batch.column("x"))
                part = of(x, batch.column("y").to_numpy())
                total = part if total is None else [t + v for t, v in zip(total, part, strict=True)]
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([np.asarray(v, float).tobytes() for v in total], pa.binary())], ["v"])

    width = 0
    out: list[np.ndarray] = []
    for i, r in enumerate(rows.mapInArrow(add, "v binary").collect()):
        width = width or len(of(np.zeros((1, 2 * len(features.STYLE))), np.zeros(1, np.int32)))
        v = np.frombuffer(bytes(r.v))
        out = [*out, v.copy()] if i < width else out
        if i >= width:
            out[i % width] += v
    return out


def _expanded(column) -> np.ndarray:
    return expand(np.frombuffer(b"".join(column.to_pylist())).reshape(len(column), len(features.STYLE)))


def bradley_terry(rows: DataFrame, p: RankParams = RankParams()) -> RankModel:
    """Newton steps on the mean loss of all pairs; rows has y and x (measures).

    A pair's loss depends on two scores only. Each pass counts the rows of both
    classes on a grid of scores, a row shared by the two places beside it, so all
    pairs of all rows count (loss within 2e-5 of a pair); the next one adds up
    slope and curvature of the rows.
    """
    d = 2 * len(features.STYLE)
    first = _sums(rows, lambda x, y: [np.array([len(y), (y == 1).sum()]), x.sum(axis=0)])
    if not first:
        return RankModel(np.zeros(d), np.ones(d), np.zeros(d), 0.0)
    n, ones = first[0]
    mean = first[1] / n
    scale = np.sqrt(_sums(rows, lambda x, y: [((x - mean) ** 2).sum(axis=0)])[0] / n)
    scale[scale < 1e-9] = 1.0
    if not ones or ones == n:
        return RankModel(mean, scale, np.zeros(d), 0.0)

    def counted(w):
        def of(x, y):
            lo, up = _place(((x - mean) / scale) @ w)
            return [np.bincount(lo[m], 1 - up[m], PLACES) + np.bincount(lo[m] + 1, up[m], PLACES) for m in (y == 1, y == 0)]

        return pair_tables(*_sums(rows, of))

    w = np.zeros(d)
    now = counted(w)
    for _ in range(p.rounds):
        _, *tables = now

        def of(x, y, w=w, tables=tables):
            z = (x - mean) / scale
            lo, up = _place(z @ w)
            at = lambda t: t[lo] * (1 - up) + t[lo + 1] * up
            good = y == 1
            slope, bend = np.where(good, -at(tables[0]), at(tables[1])), np.where(good, at(tables[2]), at(tables[3]))
            mixed = [np.zeros((CROSS, z.shape[1])) for _ in range(2)]
            for m, c in zip(mixed, (good, ~good), strict=True):
                np.add.at(m, lo[c] * CROSS // PLACES, z[c])
            return [slope @ z, ((z * bend[:, None]).T @ z).ravel(), *(m.ravel() for m in mixed)]

        g, h, up, down = _sums(rows, of)
        step = -np.linalg.solve(curvature(h, up, down, n, ones, p.l2), g + p.l2 * w)
        value, drop, size = now[0] + p.l2 / 2 * w @ w, (g + p.l2 * w) @ step, 1.0
        while True:
            then = counted(w + size * step)
            gained = value - then[0] - p.l2 / 2 * (w + size * step) @ (w + size * step)
            if gained >= -1e-4 * size * drop or size < 1e-3:
                break
            size /= 2
        if gained <= 0:
            break
        w, now = w + size * step, then
        if gained < 1e-5 * value:
            break
    edge = threshold(rows, lambda x: ((x - mean) / scale) @ w, 1 - ones / n)
    return RankModel(mean, scale, w, float(np.log(p.cut / (1 - p.cut))) - edge)


def curvature(h: np.ndarray, up: np.ndarray, down: np.ndarray, n: float, ones: float, l2: float) -> np.ndarray:
    """Curvature of the mean pair loss: its rows' part less what a pair's two rows
    share, that from sums on a coarser grid; never less than l2 in any direction."""
    d = int(np.sqrt(len(h)))
    up, down = up.reshape(CROSS, d), down.reshape(CROSS, d)
    gap = np.subtract.outer(np.arange(CROSS), np.arange(CROSS)) * (STEP * PLACES / CROSS)
    lose = 1.0 / (1.0 + np.exp(gap))
    both = up.T @ (lose * (1 - lose)) @ down / (ones * (n - ones))
    value, vector = np.linalg.eigh(h.reshape(d, d) - both - both.T)
    return (vector * (np.maximum(value, 0.0) + l2)) @ vector.T


def threshold(rows: DataFrame, raw, share: float) -> float:
    """The quantile of all rows' scores, half-way to the next score above: exact,
    by counts in ever finer ranges around the rank."""

    def find(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(raw(_expanded(batch.column("x"))))], ["s"])

    scores = materialise(rows.mapInArrow(find, "s double"), "quality-scores")
    n, low, high = scores.agg(F.count("s"), F.min("s"), F.max("s")).first()
    rank = share * (n - 1)

    def at(k: int) -> float:
        lo, hi = low, high
        while lo < hi:
            inside = scores.where(F.col("s").between(lo, hi))
            parts = inside.groupBy(F.floor((F.col("s") - lo) / (hi - lo) * 4096).alias("b")).agg(F.count("*").alias("n"), F.min("s").alias("lo"), F.max("s").alias("hi")).orderBy("b").collect()
            for r in parts:
                if k < r.n:
                    break
                k -= r.n
            if (r.lo, r.hi) == (lo, hi):
                break
            lo, hi = r.lo, r.hi
        return lo

    k = int(rank)
    edge, next_up = at(k), at(min(k + 1, n - 1))
    edge += (next_up - edge) * (rank - k)
    # Between the classes the exact place is free: half-way to the next score up.
    above = scores.where(F.col("s") > edge).agg(F.min("s")).first()[0]
    return edge if above is None else (edge + above) / 2


def measures(docs: DataFrame) -> DataFrame:
    """doc_id and style measures of every row, written once."""
    prepare(docs.sparkSession)

    def extract(batches):
        for batch in batches:
            x = features.style(batch.column("text"))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([r.tobytes() for r in x], pa.binary())], ["doc_id", "x"])

    return materialise(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(extract, "doc_id long, x binary"), "quality-measures")


def train_on(measured: DataFrame, labels: DataFrame, label: str = "quality", params: RankParams = RankParams()) -> RankModel:
    """The model of all labelled rows that aren't held out."""
    rows = measured.join(labelled(labels, label), F.col("doc_id") == F.col("l_id")).select("y", "x")
    return bradley_terry(materialise(rows, "quality-rows"), params)


def train(docs: DataFrame, labels: DataFrame, label: str = "quality", params: RankParams = RankParams()) -> RankModel:
    return train_on(measures(docs), labels, label, params)


def score_measured(measured: DataFrame, model: RankModel, cut: float = 0.3) -> DataFrame:
    """``score`` of rows whose measures are there already."""
    shared = measured.sparkSession.sparkContext.broadcast(model)

    @F.arrow_udf("double")
    def f(x: pa.Array) -> pa.Array:
        return pa.array(shared.value.scores(_expanded(x)))

    return _scored(measured, f("x"), cut)


def score(docs: DataFrame, model: RankModel, cut: float = 0.3) -> DataFrame:
    """doc_id, held_out, score, predicted of every row of ``docs``."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.arrow_udf("double")
    def f(text: pa.Array) -> pa.Array:
        return pa.array(shared.value.scores(expand(features.style(text))))

    return _scored(docs, f("text"), cut)


def _scored(rows: DataFrame, value, cut: float) -> DataFrame:
    return rows.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), value.alias("score")).withColumn("predicted", (F.col("score") >= cut).cast("int"))
