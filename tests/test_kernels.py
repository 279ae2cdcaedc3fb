"""The map, merging and baselines without Spark: worked examples and invariants."""

import numpy as np
import pytest

from driftclust.operators import baselines, growing_map, merging
from driftclust.operators.growing_map import GrowingMap
from driftclust.params import Params


def ari(a, b):
    a, b = np.unique(a, return_inverse=True)[1], np.unique(b, return_inverse=True)[1]
    c = np.zeros((a.max() + 1, b.max() + 1))
    np.add.at(c, (a, b), 1)
    pairs = lambda v: float((v * (v - 1) / 2).sum())
    e = pairs(c.sum(1)) * pairs(c.sum(0)) / (len(a) * (len(a) - 1) / 2)
    top = (pairs(c.sum(1)) + pairs(c.sum(0))) / 2
    return (pairs(c.ravel()) - e) / (top - e) if top != e else 1.0


def mixture(seed, spread=0.06, sizes=(1192, 506, 242, 60)):
    rng = np.random.default_rng(seed)
    centres = [(0.2, 0.2), (0.8, 0.2), (0.2, 0.8), (0.8, 0.8)]
    x = np.vstack([rng.normal(c, spread, (n, 2)) for c, n in zip(centres, sizes, strict=True)])
    return x, np.repeat(np.arange(4), sizes)


@pytest.mark.parametrize(
    "n_i,n_j,sd,gap",
    [(100, 100, 0.10, 67262.18), (100, 100, 0.25, 4.630404), (100, 100, 0.50, 2.207831), (100, 10, 0.25, 10.060709), (1000, 10, 0.10, 377520.7)],
)
def test_gap_of_worked_examples(n_i, n_j, sd, gap):
    assert np.exp(-merging.log_mixture(n_i, sd**2, n_j, sd**2).min()) == pytest.approx(gap, rel=1e-5)


def test_gap_from_statistics_equals_direct_projection():
    x, y = mixture(3)
    c = merging.cell_stats(x, y, 4)
    a, b = x[y == 0], x[y == 1]
    u = merging.project(np.vstack([a, b]), a.mean(0), b.mean(0))
    direct = -merging.log_mixture(len(a), u[: len(a)].var(), len(b), u[len(a) :].var()).min()
    assert merging.log_gap(c, 0, 1) == pytest.approx(direct, rel=1e-9)
    assert u[: len(a)].mean() == pytest.approx(0.5) and u[len(a) :].mean() == pytest.approx(-0.5)


def test_same_centre_merges_first_and_single_points_have_finite_gaps():
    c = merging.cell_stats(np.array([[0.0, 0], [0.0, 0], [1.0, 1]]), np.array([0, 1, 2]), 3)
    assert merging.log_gap(c, 0, 1) == -np.inf and np.isfinite(merging.log_gap(c, 0, 2))


def test_separability_example():
    x = np.array([[0.0], [1.0], [10.0], [11.0]])
    cross = merging.cross_counts(merging.neighbours(x, 1), np.arange(4), 4)
    assert merging.separability(cross, np.array([0, 0, 1, 1]), 1) == 0
    assert merging.separability(cross, np.array([0, 1, 1, 1]), 1) == 1


def triangle(points, strain, subnet=0):
    m = GrowingMap.empty(2)
    for p, s in zip(points, strain, strict=True):
        m.add(np.array(p, float), subnet, s)
    for a, b in ((0, 1), (1, 2), (0, 2)):
        m.link(a, b)
    return m


def test_split_halves_the_edge_and_keeps_total_strain():
    m = triangle([(0, 0), (4, 0), (2, 1)], [5.0, 2.0, 1.0])
    h = m.split(0, 1)
    assert m.w[h].tolist() == [2, 0] and m.nbrs[h] == {0, 1, 2} and 1 not in m.nbrs[0]
    assert m.strain.sum() == pytest.approx(8.0)


def test_join_links_two_subnets_into_one():
    m = triangle([(0, 0), (5, 0), (0, 5)], [9.0, 0, 0])
    ids = [m.add(np.array(p, float), 1, 1.0) for p in ((1, 0), (6, 1), (1, 6))]
    for a, b in ((0, 1), (1, 2), (0, 2)):
        m.link(ids[a], ids[b])
    before = len(m.edges())
    assert m.step(Params()) == "join"
    assert len(set(m.subnet.tolist())) == 1 and len(m.edges()) == before + 2


def test_one_step_pull_and_strain():
    m = triangle([(0, 0), (4, 0), (2, 1)], [1.0, 2.0, 3.0])
    assert m.visit(np.array([0.5, 0.0]), Params()) == 0
    assert m.w[0].tolist() == [0.3, 0.0] and m.w[1].tolist() == pytest.approx([3.93, 0.0])
    assert m.strain.tolist() == pytest.approx([1.5, 1.99, 2.985])


def test_training_counts_and_replay():
    x, _ = mixture(1)
    a, b = growing_map.fit(x, Params()), growing_map.fit(x, Params())
    assert a.steps == len(x) // 100 and (a.w == b.w).all() and a.q == 45 + a.splits
    assert growing_map.fit(x, Params(subnets=1, join=False, grow=False)).q == 3


def test_poisson_seeds_keep_their_distance():
    x, _ = mixture(2)
    got = x[growing_map.seeds(x[:500], 15)]
    d = growing_map.sq_distances(got, got)[np.triu_indices(15, 1)]
    other = x[growing_map.seeds(x[:500], 15, "random")]
    assert len(got) == 15 and d.min() > growing_map.sq_distances(other, other)[np.triu_indices(15, 1)].min()


def test_nearest_is_the_argmin_with_ties_to_the_lowest():
    rng = np.random.default_rng(0)
    x, w = rng.random((300, 5)), rng.random((40, 5))
    w[7] = w[3]
    win, dist = growing_map.nearest(x, w)
    d = growing_map.sq_distances(x, w)
    assert (win == d.argmin(axis=1)).all() and np.allclose(dist, np.sqrt(d.min(axis=1)))


def test_schedules_agree_on_one_complete_subnet():
    x, _ = mixture(5, sizes=(60, 40, 30, 20))
    w = x[::10]
    cell, _ = growing_map.nearest(x, w)
    c = merging.cell_stats(x, cell, len(w))
    every = [(a, b) for a in range(len(w)) for b in range(a + 1, len(w))]
    cross = merging.cross_counts(merging.neighbours(x, 10), cell, len(w))
    traces = [merging.run(c, np.zeros(len(w), int), every, cross, 10, Params(schedule=s)) for s in ("guided", "two_stage", "adjacent", "all_pairs")]
    for t in traces[1:]:
        assert (t.k, t.a, t.b) == (traces[0].k, traces[0].a, traces[0].b)
    t = traces[0]
    for k in (2, 4, 7):
        assert t.omega[t.k.index(k)] == pytest.approx(merging.separability(cross, np.where(c.n > 0, t.groups(k), -1), 10))


def test_method_finds_imbalanced_clusters():
    good = 0
    for seed in range(6):
        x, y = mixture(seed)
        p = Params(seed=seed)
        m = growing_map.fit(x, p)
        cell, _ = growing_map.nearest(x, m.w)
        t = merging.run(merging.cell_stats(x, cell, m.q), m.subnet, m.edges(), merging.cross_counts(merging.neighbours(x, 10), cell, m.q), 10, p)
        k = merging.best_k(np.array(t.k), np.array(t.log_theta), np.array(t.omega))
        good += ari(y, t.groups(k)[cell]) > 0.9
    assert good >= 5


@pytest.mark.parametrize("name", list(baselines.METHODS))
def test_baselines_label_every_point(name):
    x, y = mixture(9, sizes=(150, 70, 40, 20))
    labels = baselines.METHODS[name][0](x, 4, seed=1)
    assert labels.shape == (280,) and labels.min() >= 0
    if name in ("kmeans", "birch", "coreset_kmeans", "multi_center", "density_peaks"):
        assert ari(y, labels) > 0.6


def test_knee_and_argmin():
    k, gap, omega = np.array([6, 5, 4, 3, 2, 1]), np.array([0.5, 0.9, 3.6, 10.7, 6.8, np.nan]), np.array([9, 7, 2, 0.5, 0.2, 0])
    assert merging.best_k(k, gap, omega) == 3
    assert merging.best_k(k, gap, omega, theta="next") == 2
    assert merging.best_k(k, gap, omega, rule="knee") in (3, 4)
    assert merging.best_k(np.array([1]), np.array([np.nan]), np.array([0.0])) == 1


def test_bad_parameters_are_refused():
    with pytest.raises(ValueError):
        Params(lr_win=0)
    with pytest.raises(ValueError):
        Params(schedule="other")
