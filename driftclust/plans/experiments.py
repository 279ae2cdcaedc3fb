"""The experiment workloads; each gives rows (dataset, method, measure, chunk_id, value)."""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baselines, metrics, sampler
from ..params import Params
from ..sources import tables
from . import pipeline

ROWS = ["dataset", "method", "measure", "chunk_id", "value"]
#: Growth and joins switched off in turn; merging switched off besides.
ABLATIONS = {
    "full": {},
    "no_subnets": {"subnets": 1, "join": False},
    "no_subnets_no_growth": {"subnets": 1, "join": False, "grow": False},
    "no_growth": {"grow": False},
    "no_merging": {"schedule": "none"},
    "all_pairs": {"schedule": "all_pairs"},
    "two_stage": {"schedule": "two_stage"},
}


def measured(points: DataFrame, clusters: DataFrame, dataset: str, method: str) -> DataFrame:
    """ARI, NMI and DBI by chunk, long."""
    return measured_each(points, clusters.withColumn("method", F.lit(method)), dataset)


def measured_each(points: DataFrame, clusters: DataFrame, dataset: str) -> DataFrame:
    """``measured`` for every method that the clusters name."""
    a = pipeline.with_truth(points, clusters).persist()  # read by every measure
    by = ["method", "chunk_id"]
    out = metrics.ari(a, by).join(metrics.nmi(a, by), by, "left").join(metrics.dbi(a, by), by, "left").join(metrics.k_error(a, by), by, "left")
    out = out.select(*by, F.expr("stack(4, 'ari', ari, 'nmi', nmi, 'dbi', dbi, 'k_error', cast(k_error as double)) as (measure, value)"))
    return out.withColumn("dataset", F.lit(dataset)).select(*ROWS)


def _all(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def run_method(points: DataFrame, method: str, k: int, p: Params = Params()) -> DataFrame:
    if method == "growing_map":
        return pipeline.cluster_chunks(points, p)
    return pipeline.baseline(points, method, k if baselines.METHODS[method][1] else 0, p.seed)


def run_whole(points: DataFrame, method: str, k: int, p: Params = Params()) -> DataFrame:
    """``run_method`` on one large set: several tasks look for its neighbours."""
    if method == "growing_map":
        return pipeline.cluster(points, p)
    return pipeline.baseline(points, method, k if baselines.METHODS[method][1] else 0, p.seed, shared=True)


def named_methods() -> list[str]:
    return ["growing_map", *(n for n, (_, _, named) in baselines.METHODS.items() if named)]


def accuracy(spark: SparkSession, sf_dir: str, sets: list[str], methods: list[str] | None = None, chunks: int = 10, ratio: int = 10, seed: int = 1) -> DataFrame:
    """Chunks of controlled imbalance from each set, every method on every chunk."""
    parts = []
    for name in sets:
        pts = sampler.stream(tables.points(spark, sf_dir, name), chunks, ratio, seed)
        parts += [measured(pts, run_method(pts, m, tables.SETS.get(name, 4)), name, m) for m in methods or named_methods()]
    return _all(parts)


def streaming_series(spark: SparkSession, sf_dir: str, chunks: int = 50, ratio: int = 2, seed: int = 1) -> DataFrame:
    """Fifty chunks of the event set, measures by chunk."""
    pts = sampler.stream(tables.points(spark, sf_dir, "lm"), chunks, ratio, seed)
    return measured(pts, pipeline.cluster_chunks(pts), "lm", "growing_map")


def ablation(spark: SparkSession, sf_dir: str, sets: list[str]) -> DataFrame:
    """Reduced variants on whole static sets."""
    variants = {variant: replace(Params(), **options) for variant, options in ABLATIONS.items()}
    return _all([measured_each(pts, pipeline.cluster_variants(pts, variants), name) for name in sets for pts in [tables.points(spark, sf_dir, name)]])


def failures(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A dense part beside a sparse one, and a uniform lattice."""
    return _all([measured(pts, run_whole(pts, m, 2), name, m) for name in ("dense", "grid") for pts in [tables.points(spark, sf_dir, name)] for m in ("growing_map", "local_peaks", "three_way", "kmeans")])


def drift(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Moving centres and turning sizes, with the map carried over and without."""
    pts = tables.points(spark, sf_dir, "drift")
    warm = pipeline.cluster_in_order(pts, replace(Params(), prune="idle")).drop("stream_key")
    return _all([measured(pts, pipeline.cluster_chunks(pts), "drift", "cold"), measured(pts, warm, "drift", "warm")])


def parameter_grid(spark: SparkSession, sf_dir: str, name: str = "ga") -> DataFrame:
    """One parameter moved at a time."""
    pts = tables.points(spark, sf_dir, name)
    grid = [("subnets", v) for v in (5, 10, 15, 30)] + [("rho", v) for v in (50, 100, 200)] + [("s", v) for v in (5, 10, 20)] + [("lr_win", v) for v in (0.05, 0.2, 0.6)]
    return measured_each(pts, pipeline.cluster_variants(pts, {f"{k}={v}": replace(Params(), **{k: v}) for k, v in grid}), name)


def efficiency(spark: SparkSession, sf_dir: str, methods: tuple[str, ...] | None = None, parts: int = 5) -> list[tuple[str, int, float]]:
    """(method, n, CPU seconds) on growing parts of one set, the last all of it."""
    pts = tables.points(spark, sf_dir, "lm").withColumn("part", F.pmod(F.xxhash64("obj_id"), F.lit(parts)))
    runs = [(m, share) for share in range(parts, 0, -1) for m in methods or named_methods()]
    took = pipeline.seconds_of(pts, runs, 5)
    return [(m, *took[m, share]) for share in range(1, parts + 1) for m in methods or named_methods()]
