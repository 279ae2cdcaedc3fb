"""Kernels do the whole job at every size."""

import numpy as np
import pytest

from driftclust.operators import baselines, growing_map, map_frames, merging
from driftclust.params import Params
from driftclust.plans import pipeline


def by_force(x, s):
    d = ((x[:, None, :] - x[None, :, :]) ** 2).sum(axis=2)
    np.fill_diagonal(d, np.inf)
    return np.sort(np.argsort(d, axis=1, kind="stable")[:, :s], axis=1)


@pytest.mark.parametrize("kind", ["mixture", "lattice", "copies", "wide"])
def test_neighbours_are_exact_with_ties_to_the_lower_index(kind):
    rng = np.random.default_rng(4)
    x = {
        "mixture": lambda: np.vstack([rng.normal(0.2, 0.01, (1200, 2)), rng.normal(0.8, 0.1, (300, 2)), rng.random((40, 2)) * 9]),
        "lattice": lambda: rng.integers(0, 8, (1500, 2)) / 8.0,
        "copies": lambda: np.repeat(rng.random((3, 2)), 400, axis=0),
        "wide": lambda: rng.random((700, 20)),
    }[kind]()
    for s in (1, 10):
        assert (merging.neighbours(x, s, 64) == by_force(x, s)).all()
    assert merging.neighbours(x[:1], 10).shape == (1, 0) and merging.neighbours(x[:3], 10).shape == (3, 2)


def test_separability_is_of_objects_beyond_6000_rows(monkeypatch):
    x = np.random.default_rng(2).random((6400, 2))
    p = Params()
    f = pipeline.fit_chunk(x, p)
    cross = merging.cross_counts(merging.neighbours(x, p.s), f.cell, f.map.q)
    t = merging.run(merging.cell_stats(x, f.cell, f.map.q), f.map.subnet, f.map.edges(), cross, p.s, p)
    assert f.trace.omega == t.omega

    def refuse(w, s):
        raise AssertionError("neurons in place of objects")

    monkeypatch.setattr(merging, "neuron_cross", refuse)
    pipeline.fit_chunk(x, p)
    baselines._merged_prototypes(x, x[:20], p)
    with pytest.raises(AssertionError):
        pipeline.fit_chunk(x, Params(separability="neuron"))


def test_sharded_fit_counts_the_objects_neighbours(spark, monkeypatch):
    rng = np.random.default_rng(7)
    x = np.vstack([rng.normal(0.2, 0.03, (500, 2)), rng.integers(0, 6, (300, 2)) / 6.0])
    df = spark.createDataFrame([(i, v) for i, v in enumerate(x.tolist())], "obj_id long, x array<double>")
    got = sorted((r.obj_id, r.nbr_id) for r in map_frames.knn_blocks(df, 10, 3).collect())
    assert got == [(i, int(j)) for i, row in enumerate(by_force(x, 10)) for j in row]

    def refuse(w, s):
        raise AssertionError("neurons in place of objects")

    monkeypatch.setattr(merging, "neuron_cross", refuse)
    assert pipeline.cluster_sharded(df, shards=2).count() == len(x)


def test_k_is_chosen_over_the_whole_trace():
    """28 far clusters; with a cap at 15 at least two would share a label."""
    rng = np.random.default_rng(3)
    centres = np.array([(i, j) for i in range(7) for j in range(4)], float)
    y = np.repeat(np.arange(28), 100)
    x = centres[y] + rng.normal(0, 0.03, (2800, 2))
    cells = merging.cell_stats(x, y, 28)
    cross = merging.cross_counts(merging.neighbours(x, 10), y, 28)
    t = merging.run(cells, np.zeros(28, int), [], cross, 10, Params(schedule="all_pairs"))
    k, theta, omega = np.array(t.k), np.array(t.log_theta), np.array(t.omega)
    assert merging.best_k(k, theta, omega) == 28 and merging.best_k(k, theta, omega, max_k=15) <= 15
    assert Params().max_k == 0


def test_initial_subnets_see_every_row():
    """Five far rows that the seeded order puts behind the first 2000."""
    x = np.random.default_rng(6).random((5000, 2))
    late = np.random.default_rng(1).permutation(5000)[-5:]
    x[late] += 50
    for how in ("poisson", "farthest"):
        m = growing_map.fit(x, Params(seeding=how, grow=False, join=False, lr_win=1e-9, lr_nbr=0))
        assert (m.w.max(axis=1) > 49).any()


def test_growth_beyond_max_neurons_is_refused():
    x = np.random.default_rng(6).random((5000, 2))
    with pytest.raises(ValueError, match="max_neurons"):
        growing_map.fit(x, Params(max_neurons=46))


def test_neighbours_compare_few_of_the_pairs(monkeypatch):
    """An outlier or a pile of copies must not bring all pairs back."""
    rng = np.random.default_rng(8)
    x = np.vstack([rng.normal(0.5, 0.03, (9000, 2)), np.repeat(rng.random((1, 2)), 3000, axis=0), rng.random((20, 2)) * 50])
    compared, real = [0], merging._sq
    monkeypatch.setattr(merging, "_sq", lambda a, b: compared.__setitem__(0, compared[0] + len(a) * len(b)) or real(a, b))
    near = merging.neighbours(x, 10)
    assert compared[0] < 0.1 * len(x) ** 2
    for i in (0, 8999, 9000, 11999, 12019):
        d = ((x - x[i]) ** 2).sum(axis=1)
        d[i] = np.inf
        assert near[i].tolist() == sorted(np.lexsort((np.arange(len(x)), d))[:10].tolist())


def test_nearest_equals_a_full_sort():
    rng = np.random.default_rng(9)
    x, w = rng.integers(0, 5, (900, 3)) / 4.0, rng.integers(0, 5, (70, 3)) / 4.0
    win, dist = growing_map.nearest(x, w)
    d = np.sqrt(((x[:, None] - w[None]) ** 2).sum(axis=2))
    assert (win == d.argmin(axis=1)).all() and (dist == d.min(axis=1)).all()


@pytest.mark.parametrize("kind", ["plain", "copies"])
def test_pair_quantile_is_exact_without_all_pairs(kind, monkeypatch):
    rng = np.random.default_rng(4)
    x = rng.random((400, 2)) if kind == "plain" else rng.integers(0, 3, (400, 2)) / 2.0
    d = growing_map.sq_distances(x, x)[np.triu_indices(400, 1)]
    for q in (0.0, 0.02, 0.37, 1.0):
        assert baselines.pair_quantile(x, q) == np.quantile(d, q)
    most, real = [0], baselines.sq_distances
    monkeypatch.setattr(baselines, "sq_distances", lambda a, b: most.__setitem__(0, max(most[0], len(a) * len(b))) or real(a, b))
    baselines.density_peaks(rng.random((3000, 2)), 3)
    assert most[0] < 3000 * 3000


def test_three_way_compares_few_of_the_pairs(monkeypatch):
    """The rest find their nearest core point without meeting all of them."""
    rng = np.random.default_rng(12)
    x = np.vstack([rng.normal(0.2, 0.03, (3000, 2)), rng.normal(0.8, 0.08, (1000, 2)), rng.integers(0, 5, (200, 2)) / 5.0])

    def refuse(*a):
        raise AssertionError("all rows against all core points")

    monkeypatch.setattr(baselines.growing_map, "nearest", refuse)
    got = baselines.three_way(x)
    rho, near = baselines.knn_density(x, 10)
    core = rho >= np.quantile(rho, 0.5)
    cores = np.flatnonzero(core)
    for i in np.flatnonzero(~core)[::7].tolist():
        assert got[i] == got[cores[((x[cores] - x[i]) ** 2).sum(axis=1).argmin()]]
    for i in cores[::7].tolist():
        assert all(got[j] == got[i] for j in near[i].tolist() if core[j] and i in near[j])
