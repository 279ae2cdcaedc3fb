"""Variants of one set share its neighbours; more axes go by products."""

from dataclasses import replace

import numpy as np
import pytest

from driftclust.operators import growing_map, merging
from driftclust.params import Params
from driftclust.plans import experiments, pipeline
from driftclust.sources import tables


def brute(x, s):
    out = np.zeros((len(x), s), np.int64)
    for i in range(len(x)):
        d = merging._sq(x[i : i + 1], x)[0]
        d[i] = np.inf
        out[i] = np.sort(np.lexsort((np.arange(len(x)), d))[:s])
    return out


def mixed(n, d, seed=3):
    rng = np.random.default_rng(seed)
    x = rng.random((n, d))
    x[:, 0] = np.round(x[:, 0], 1)
    return np.vstack([x, x[: n // 4], np.round(x[: n // 4], 1)])


@pytest.mark.parametrize("d", [2, 5, 8])
def test_neighbours_on_more_axes_and_in_shares(d):
    x = mixed(4000, d)
    want = brute(x, 10)
    assert (merging.neighbours(x, 10) == want).all()
    rows = [merging.share_of_rows(x, i, 3) for i in range(3)]
    assert sorted(np.concatenate(rows).tolist()) == list(range(len(x)))
    assert all((merging.neighbours(x, 10, rows=r) == want[r]).all() for r in rows)
    assert (merging.fewer(x, want, 4) == brute(x, 4)).all()


def test_winners_of_many_rows_and_neurons():
    x, w = mixed(6000, 7), np.vstack([mixed(400, 7, 5), mixed(400, 7, 5)])
    win, dist = growing_map.nearest(x, w)
    d = merging._sq(x, w)
    assert (win == d.argmin(axis=1)).all() and np.allclose(dist, np.sqrt(d.min(axis=1)))


def test_variants_equal_runs_of_their_own(spark, sf):
    pts = tables.points(spark, sf, "wc").where("obj_id % 3000 < 1500").cache()
    variants = {"full": Params(), "s=5": replace(Params(), s=5), "all_pairs": replace(Params(), schedule="all_pairs")}
    got = {tuple(r) for r in pipeline.cluster_variants(pts, variants).select("method", "chunk_id", "obj_id", "cluster").collect()}
    want = {(m, *r) for m, p in variants.items() for r in pipeline.cluster_chunks(pts, p).collect()}
    assert got == want


@pytest.mark.parametrize("run", [lambda s, d: experiments.ablation(s, d, ["wc"]), experiments.parameter_grid])
def test_neighbours_are_looked_for_once_a_set(spark, sf, run):
    plan = run(spark, sf)._jdf.queryExecution().analyzed().toString()
    assert plan.count("FlatMapCoGroupsIn") >= 1 and "Union" not in plan


def test_efficiency_times_all_runs_in_one_job(spark, sf):
    spark.sparkContext.setJobGroup("efficiency", "")
    got = experiments.efficiency(spark, sf, ("kmeans", "granule_tree"), parts=2)
    jobs = spark.sparkContext.statusTracker().getJobIdsForGroup("efficiency")
    assert [r[0] for r in got] == ["kmeans", "granule_tree"] * 2 and got[0][1] == got[1][1] < got[2][1] == got[3][1] == 10000
    assert all(r[2] > 0 for r in got) and len(jobs) < 10
