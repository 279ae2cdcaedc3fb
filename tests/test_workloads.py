"""The registered workloads cover all sets, chunks and named methods."""

import pytest

from driftclust import queries as Q
from driftclust.plans import experiments
from driftclust.sources import tables


@pytest.mark.parametrize("name", ["workload_accuracy", "workload_ranks"])
def test_accuracy_runs_over_everything(spark, sf, name, monkeypatch):
    asked = []
    empty = spark.createDataFrame([], "dataset string, method string, measure string, chunk_id long, value double")
    monkeypatch.setattr(experiments.sampler, "stream", lambda pts, chunks, ratio, seed: asked.append(chunks) or pts)
    monkeypatch.setattr(experiments, "run_method", lambda pts, m, k: (pts, m))
    monkeypatch.setattr(experiments, "measured", lambda pts, got, s, m: asked.append((s, m)) or empty)
    monkeypatch.setattr(experiments.tables, "points", lambda *a: None)
    Q.queries()[name](spark, sf)
    assert [a for a in asked if a == 10] == [10] * len(tables.SETS)
    assert {a for a in asked if a != 10} == {(s, m) for s in tables.SETS for m in experiments.named_methods()}


def test_ablation_and_efficiency_are_registered(spark, sf, monkeypatch):
    seen = []
    monkeypatch.setattr(experiments, "ablation", lambda s, d, sets: seen.append(sets))
    Q.queries()["workload_ablation"](spark, sf)
    assert seen == [list(tables.SETS)]
    part = experiments.efficiency(spark, sf, ("kmeans",), parts=2)
    assert [r[:1] for r in part] == [("kmeans",)] * 2 and part[-1][1] == 10000


def test_stand_in_sets_are_whole(spark, sf):
    n = spark.read.parquet(f"{sf}/lineitem.parquet").count()
    assert [tables.points(spark, sf, s).count() for s in ("ab", "ra", "se")] == [n] * 3
