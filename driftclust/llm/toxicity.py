"""Toxicity: FTRL-proximal logistic regression over hashed word n-grams and skip-grams.

Words, adjacent word pairs and pairs with one word between are hashed into
2**bits slots, a document has the slots that occur in it. Training goes through
a bounded sample of the labelled rows one at a time; each coordinate has its own
learning rate, and L1 keeps most weights at exactly 0. The weights that remain
are broadcast; at most 2**bits of them can exist. Scoring is one map over the
documents, without a shuffle.

Null and empty texts have no features and score as the bias alone. Without
labelled rows of both classes the model is its prior (0.5 without any label).
Rows with a repeated doc_id are scored each; extra columns are ignored.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import features, kernels
from .labelled import held_out, sample
from .scratch import lean, materialise, prepare


@dataclass(frozen=True)
class FtrlParams:
    bits: int = 20
    alpha: float = 1.0
    beta: float = 1.0
    l1: float = 20.0
    l2: float = 1.0
    epochs: int = 3
    #: Weight of a row labelled 1: most rows are labelled 0.
    positive: float = 3.0
    #: At most so many labelled rows are trained on.
    max_rows: int = 20_000


@dataclass(frozen=True)
class LinearModel:
    bits: int
    bias: float
    slot: np.ndarray
    weight: np.ndarray

    def dense(self) -> np.ndarray:
        w = np.zeros(1 << self.bits, np.float32)
        w[self.slot] = self.weight
        return w


def ftrl(examples: list[tuple[np.ndarray, int]], p: FtrlParams) -> LinearModel:
    """Weights after ``epochs`` passes; the last slot of z and n is the bias."""
    size = (1 << p.bits) + 1
    z, n = np.zeros(size), np.zeros(size)

    def weights(i):
        zi = z[i]
        w = -(zi - np.sign(zi) * p.l1) / ((p.beta + np.sqrt(n[i])) / p.alpha + p.l2)
        w[np.abs(zi) <= p.l1] = 0.0
        return w

    for _ in range(p.epochs):
        for slots, y in examples:
            i = np.append(slots, size - 1)
            w = weights(i)
            w[-1] = -z[-1] / ((p.beta + np.sqrt(n[-1])) / p.alpha)
            g = 1.0 / (1.0 + np.exp(-np.clip(w.sum(), -35, 35))) - y
            g *= p.positive if y else 1.0
            grown = np.sqrt(n[i] + g * g)
            z[i] += g - (grown - np.sqrt(n[i])) / p.alpha * w
            n[i] += g * g
    w = weights(np.arange(size - 1))
    kept = np.flatnonzero(w)
    return LinearModel(p.bits, float(-z[-1] / ((p.beta + np.sqrt(n[-1])) / p.alpha)), kept, w[kept].astype(np.float32))


def train(docs: DataFrame, labels: DataFrame, label: str = "toxic", params: FtrlParams = FtrlParams()) -> LinearModel:
    """Fit on a bounded sample: features on all executors, the passes in one task."""
    prepare(docs.sparkSession)
    bits = params.bits

    def extract(batches):
        for batch in batches:
            sets = [s.astype(np.int32).tobytes() for _, s in features.presence(batch.column("text"), bits)]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("y"), pa.array(sets, pa.binary())], ["doc_id", "y", "slots"])

    def fit(batches):
        # The examples stay views of the batches' buffers: a worker lives on
        # after this task, and what it holds in many small pieces stays with it.
        rows = []
        for b in batches:
            data, off = kernels.utf8(b.column("slots"))
            rows += [(i, y, data[lo:hi].view(np.int32)) for i, y, lo, hi in zip(b.column("doc_id").to_pylist(), b.column("y").to_pylist(), off[:-1].tolist(), off[1:].tolist(), strict=True)]
        times = Counter(r[0] for r in rows)
        rows.sort(key=lambda r: ((r[0] * 0x9E3779B1) & 0xFFFFFFFF, r[0], r[1], r[2].tobytes() if times[r[0]] > 1 else b""))
        m = ftrl([(s, y) for _, y, s in rows], params)
        yield pa.RecordBatch.from_arrays([pa.array([m.bias]), pa.array([m.slot.astype(np.int64).tobytes()], pa.binary()), pa.array([m.weight.tobytes()], pa.binary())], ["bias", "slot", "weight"])

    rows = sample(docs, labels, label, params.max_rows)
    found = materialise(rows.mapInArrow(lean(extract), "doc_id long, y int, slots binary"), "toxicity-sample")
    got = found.coalesce(1).mapInArrow(lean(fit), "bias double, slot binary, weight binary").collect()
    if not got:
        return LinearModel(bits, 0.0, np.zeros(0, np.int64), np.zeros(0, np.float32))
    return LinearModel(bits, got[0].bias, np.frombuffer(bytes(got[0].slot), np.int64), np.frombuffer(bytes(got[0].weight), np.float32))


def score_column(spark, model: LinearModel):
    """A column function: text -> probability of the label."""
    shared = spark.sparkContext.broadcast(model)
    cache: list[np.ndarray] = []

    @F.arrow_udf("double")
    def score(text: pa.Array) -> pa.Array:
        if not cache:
            cache.append(shared.value.dense())
        s = features.linear_scores(text, cache[0], shared.value.bits) + shared.value.bias
        return pa.array(1.0 / (1.0 + np.exp(-np.clip(s, -35, 35))))

    return score


def score(docs: DataFrame, model: LinearModel) -> DataFrame:
    """doc_id, held_out, score, predicted of every row of ``docs``."""
    f = score_column(docs.sparkSession, model)
    return docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), f("text").alias("score")).withColumn("predicted", (F.col("score") >= 0.5).cast("int"))


def remove_toxic(docs: DataFrame, model: LinearModel, threshold: float = 0.5) -> DataFrame:
    """``docs`` without the documents scored at the threshold or above."""
    prepare(docs.sparkSession)
    f = score_column(docs.sparkSession, model)
    return docs.withColumn("__toxic", f("text")).where(F.col("__toxic") < threshold).drop("__toxic")
