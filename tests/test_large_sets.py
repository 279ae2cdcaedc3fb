"""Kernels and measures keep to the exact result with work that fits large sets."""

import numpy as np
import pytest

from driftclust.operators import baselines, growing_map, merging, metrics
from driftclust.params import Params
from driftclust.plans import experiments, pipeline


def points(n, seed=3):
    rng = np.random.default_rng(seed)
    x = np.vstack([rng.normal(0.2, 0.03, (n // 2, 2)), rng.normal(0.8, 0.08, (n // 3, 2)), rng.integers(0, 5, (n - n // 2 - n // 3, 2)) / 5.0])
    return x[rng.permutation(n)]


def merged_by_force(c, floor):
    c, alive, out = c.copy(), np.flatnonzero(c.n > 0).tolist(), []
    while len(alive) > 1:
        out.append(min((merging.log_gap(c, a, b, floor), a, b) for i, a in enumerate(alive) for b in alive[i + 1 :]))
        c.add(*out[-1][1:])
        alive.remove(out[-1][2])
    return out


@pytest.mark.parametrize("copies", [False, True])
def test_all_pairs_are_merged_as_by_force_with_few_gaps_in_full(copies, monkeypatch):
    x = points(600)
    cell = np.arange(600) % 60 if copies else growing_map.nearest(x, x[:60])[0]
    if copies:
        x = x[cell % 7]
    c = merging.cell_stats(x, cell, 60)
    full, real = [0], merging.Gaps.exact
    monkeypatch.setattr(merging.Gaps, "exact", lambda self, a, js: full.__setitem__(0, full[0] + len(js)) or real(self, a, js))
    t = merging.run(c, np.zeros(60, int), [], merging.cross_pairs(merging.neighbours(x, 10), cell, 60), 10, Params(schedule="all_pairs"))
    want = merged_by_force(c, 1e-6)
    assert list(zip(t.a, t.b, strict=True))[:-1] == [w[1:] for w in want]
    assert np.allclose(t.log_theta[:-1], [w[0] for w in want])
    assert copies or full[0] < t.gaps / 2


def test_counts_between_cells_without_a_square():
    x = points(900)
    cell = growing_map.nearest(x, x[:50])[0]
    near = merging.neighbours(x, 10)
    a, b, n = merging.cross_pairs(near, cell, 50)
    dense = merging.cross_counts(near, cell, 50)
    assert (dense[a, b] == n).all() and dense.sum() == n.sum()
    g = np.arange(50) % 4
    assert merging.separability((a, b, n), g, 10) == merging.separability(dense, g, 10) > 0


def test_a_map_grows_as_far_as_training_asks():
    """With a limit of 4,096 neurons by default this was an error."""
    x = points(4400)
    m = growing_map.fit(x, Params(rho=1, join=False, subnets=1))
    assert m.q > 4096
    assert pipeline.fit_chunk(x[:300], Params(rho=1)).k >= 1


def test_nearest_meets_few_neurons(monkeypatch):
    x, w = points(30_000), points(1000, 5)
    d = merging._sq(x, w)
    met, real = [0], merging._sq
    monkeypatch.setattr(merging, "_sq", lambda a, b: met.__setitem__(0, met[0] + len(a) * len(b)) or real(a, b))
    win, dist = growing_map.nearest(x, w)
    assert (win == d.argmin(axis=1)).all() and np.allclose(dist, np.sqrt(d.min(axis=1)))
    assert 0 < met[0] < 0.5 * len(x) * len(w)


@pytest.mark.parametrize("density", ["knn", "ties"])
def test_denser_points_are_found_among_few(density, monkeypatch):
    x = points(9000)
    rho = baselines.knn_density(x, 10)[0] if density == "knn" else np.round(np.random.default_rng(1).random(len(x)), 1)
    met, real = [0], merging._sq
    monkeypatch.setattr(merging, "_sq", lambda a, b: met.__setitem__(0, met[0] + len(a) * len(b)) or real(a, b))
    parent, delta, order = baselines._denser(x, rho)
    assert 0 < met[0] < 0.3 * len(x) ** 2 / 2
    assert (order == np.lexsort((np.arange(len(x)), -rho))).all()
    for at in range(1, len(x), 37):
        d = ((x[order[:at]] - x[order[at]]) ** 2).sum(axis=1)
        assert parent[order[at]] == order[int(d.argmin())] and delta[order[at]] == np.sqrt(d.min())


def test_soinn_sorts_no_nodes(monkeypatch):
    """Two nearest nodes need no order of all; links are kept by node."""
    x = points(3000)

    def refuse(*a, **k):
        raise AssertionError("all nodes sorted for one point")

    monkeypatch.setattr(np, "argsort", refuse)
    labels = baselines.density_soinn(x)
    assert len(labels) == len(x) and len(np.unique(labels)) > 1


def test_dbi_with_many_clusters(spark):
    """4,000 clusters are 16 million pairs; coinciding centres are skipped."""
    rng = np.random.default_rng(2)
    x = np.vstack([np.repeat(rng.integers(0, 9, (300, 2)) / 8.0, 2, axis=0), rng.random((5400, 2))])
    cluster = np.arange(len(x)) // 2
    rows = [(0, int(c), v) for c, v in zip(cluster, x.tolist(), strict=True)] + [(1, 0, [0.0, 0.0])]
    got = metrics.dbi(spark.createDataFrame(rows, "chunk_id long, cluster long, x array<double>"), ["chunk_id"])
    assert "CartesianProduct" not in (plan := got._jdf.queryExecution().optimizedPlan().toString()) and plan.count("Join") < 4
    c = x.reshape(-1, 2, 2).mean(axis=1)
    s = np.sqrt(((x.reshape(-1, 2, 2) - c[:, None]) ** 2).sum(axis=2)).mean(axis=1)
    gap = np.sqrt(((c[:, None] - c[None]) ** 2).sum(axis=2))
    with np.errstate(divide="ignore", invalid="ignore"):
        want = np.where(gap > 0, (s[:, None] + s) / gap, -1).max(axis=1).mean()
    out = got.collect()
    assert [r.chunk_id for r in out] == [0] and out[0].dbi == pytest.approx(want, rel=1e-9)


def test_predict_fits_the_model_once(spark):
    df = spark.createDataFrame([(0, i, v) for i, v in enumerate(points(300).tolist())], "chunk_id long, obj_id long, x array<double>")
    fits = spark.sparkContext.accumulator(0)

    def fit(part):
        fits.add(1)
        return part.iloc[:2].assign(neuron=[0, 1], cluster=[0, 1], w=list(part["x"].iloc[:2]))[["neuron", "cluster", "w"]]

    model = df.groupBy("chunk_id").applyInPandas(fit, "neuron long, cluster int, w array<double>")
    assert pipeline.predict(df, model).count() == 300
    assert fits.value == 1


def test_sharded_cells_cross_as_pairs(spark, monkeypatch):
    """The driver holds a count for each pair of cells that meet, no table of all pairs."""
    rng = np.random.default_rng(4)
    x = np.vstack([rng.normal(c, 0.03, (300, 2)) for c in ((0.2, 0.2), (0.8, 0.8))])
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "obj_id long, x array<double>")
    held = []
    choose = pipeline.choose
    monkeypatch.setattr(pipeline, "choose", lambda m, cell, cells, cross, s, p: held.append((m, cells, cross)) or choose(m, cell, cells, cross, s, p))
    got = {r.obj_id: r.cluster for r in pipeline.cluster_sharded(df, shards=2).collect()}
    m, cells, cross = held[0]
    assert isinstance(cross, tuple) and len(cross[0]) < m.q * m.q
    cell = growing_map.nearest(x, m.w)[0]
    whole = merging.cell_stats(x, cell, m.q)
    assert (cells.n == whole.n).all() and np.allclose(cells.s1, whole.s1) and np.allclose(cells.s2, whole.s2)
    table = np.zeros((m.q, m.q))
    table[cross[0], cross[1]] = cross[2]
    assert (table == merging.cross_counts(merging.neighbours(x, 10), cell, m.q)).all()
    assert len(got) == len(x) and len(set(got.values())) == 2


@pytest.mark.parametrize("d", [1, 2, 4])
def test_cutoff_density_looks_into_boxes_at_its_edge_only(d, monkeypatch):
    rng = np.random.default_rng(d)
    x = np.vstack([rng.normal(0.3, 0.05, (900, d)), rng.integers(0, 6, (600, d)) / 6.0, np.full((40, d), 0.5)])
    every = ((x[:, None, :] - x[None, :, :]) ** 2).sum(axis=2)
    upper = every[np.triu_indices(len(x), 1)]
    for q in (0.0, 0.02, 0.3, 1.0):
        assert baselines.pair_quantile(x, q, bins=64) == np.quantile(upper, q)
    for d2 in (0.0, float(np.quantile(upper, 0.02)), 1e-3, 10.0):
        assert (baselines.count_within(x, d2) == (every < d2).sum(axis=1)).all()
    made, sq = [], merging._sq
    monkeypatch.setattr(merging, "_sq", lambda a, b: made.append(len(a) * len(b)) or sq(a, b))
    monkeypatch.setattr(baselines, "_row_blocks", lambda *a: pytest.fail("all pairs"))
    wide = rng.normal(0.5, 0.2, (6000, 2))
    baselines.density_peaks(wide, 4)
    assert sum(made) < 6000 * 6000 * 0.75


@pytest.mark.parametrize("d", [1, 2, 3])
def test_objects_taken_together_train_as_one_at_a_time(d, monkeypatch):
    """A large map compares an object with neurons near it, and ends up the same."""
    rng = np.random.default_rng(d)
    x = np.vstack([rng.normal(0.3, 0.05, (9000, d)), rng.random((3000, d)), rng.integers(0, 4, (2000, d)) / 4.0, rng.normal(0.9, 0.002, (3000, d))])
    p = Params(rho=20)
    one = growing_map.fit(x[::2] + 0.1, p, growing_map.fit(x, p))
    compared = []
    few = growing_map.Places.few
    monkeypatch.setattr(growing_map.Places, "few", lambda self, *a: compared.append(len(a[0])) or few(self, *a))
    monkeypatch.setattr(growing_map, "LARGE", 60)
    got = growing_map.fit(x[::2] + 0.1, p, growing_map.fit(x, p))
    assert sum(compared) > 10_000 and got.edges() == one.edges() and got.distances == one.distances
    assert (got.w == one.w).all() and (got.hits == one.hits).all() and (got.subnet == one.subnet).all()
    assert np.allclose(got.strain, one.strain, rtol=1e-9, atol=0)


def test_bridges_over_empty_cells_by_parts():
    rng = np.random.default_rng(2)
    edges = [(int(a), int(b)) for a, b in rng.integers(0, 60, (90, 2)) if a != b]
    n = rng.integers(0, 2, 60)
    near = {i: set() for i in range(60)}
    for a, b in edges:
        near[a].add(b)
        near[b].add(a)
    for dead in np.flatnonzero(n == 0).tolist():
        around = near.pop(dead)
        for a in around & set(near):
            near[a] = (near[a] | around) - {a, dead}
    assert merging.bridged(edges, n) == {(min(a, b), max(a, b)) for a, bs in near.items() for b in bs if b in near}


def test_warm_chunks_are_tasks_of_their_own(spark):
    """Only training goes through the chunks in turn; one set's neighbours are shared."""
    rng = np.random.default_rng(6)
    rows = [(c, c * 1000 + i, v.tolist()) for c in range(6) for i, v in enumerate(rng.normal(0.2 + 0.05 * c + 0.5 * (rng.random(400) < 0.3)[:, None], 0.03, (400, 2)))]
    df = spark.createDataFrame(rows, "chunk_id long, obj_id long, x array<double>")
    p = Params(prune="idle", idle_chunks=2)
    out = pipeline.cluster_in_order(df, p)
    assert "FlatMapCoGroupsIn" in out._jdf.queryExecution().analyzed().toString()
    state, won, want = None, {}, {}
    for c in range(6):
        x = np.array([v for d, _, v in rows if d == c])
        f = pipeline.fit_chunk(x, Params(), state)
        want |= {c * 1000 + i: int(v) for i, v in enumerate(f.labels)}
        state = f.map
        won |= {s: c for s in set(state.subnet.tolist()) if state.hits[state.subnet == s].sum() >= p.min_hits}
        gone = np.array([c - won.get(int(s), c) >= p.idle_chunks for s in state.subnet])
        if gone.any() and not gone.all():
            state.drop(gone)
    assert {r.obj_id: r.cluster for r in out.collect()} == want
    one = pipeline.cluster(df)
    assert "FlatMapCoGroupsIn" in one._jdf.queryExecution().analyzed().toString()
    x = np.array([v for _, _, v in rows])
    assert [r.cluster for r in one.orderBy("obj_id").collect()] == pipeline.fit_chunk(x, Params()).labels.tolist()


@pytest.mark.parametrize("method", ["growing_map", "local_peaks", "three_way", "kmeans"])
def test_whole_sets_share_the_search_for_neighbours(spark, method):
    x = points(900)
    df = spark.createDataFrame([(0, i, v.tolist()) for i, v in enumerate(x)], "chunk_id long, obj_id long, x array<double>")
    whole = experiments.run_whole(df, method, 2)
    assert ("FlatMapCoGroupsIn" in whole._jdf.queryExecution().analyzed().toString()) == (method != "kmeans")
    assert sorted(whole.collect()) == sorted(experiments.run_method(df, method, 2).collect())
