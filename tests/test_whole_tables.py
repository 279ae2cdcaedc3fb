"""Queries over whole tables against their SQL: no id range is cut out."""

import glob
import os

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from driftclust import queries as Q
from driftclust.operators import map_frames
from driftclust.sources import tables

WHOLE = [
    "knn10_embeddings_all", "cell_cross_counts_all", "omega_embeddings_labels_all", "fknn_density_all",
    "dpc_density_embeddings_all", "dpc_delta_embeddings_all", "win_ranking_all", "planted_id_orders_all",
]


def norm(rows):
    return sorted(tuple(repr(round(v, 9) + 0.0) if isinstance(v, float) else str(v) for v in r) for r in rows)


@pytest.mark.parametrize("name", WHOLE)
def test_whole_table_query_equals_sql(spark, sf, name):
    c = duckdb.connect()
    for f in glob.glob(f"{sf}/*.parquet"):
        c.sql(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    sql = Q.oracle_sql()[name]
    assert "vec_id < 400" not in sql and "vec_id < 300" not in sql and "o_orderkey <" not in sql
    df = Q.queries()[name](spark, sf)
    cols = sorted(df.columns)
    got = [tuple(r) for r in df.select(*cols).collect()]
    assert norm(got) == norm(c.sql(f"select {','.join(cols)} from ({sql})").fetchall())


def test_planted_sets_hold_every_order(spark, sf):
    n = spark.read.parquet(f"{sf}/orders.parquet").count()
    for name in ("id", "dense", "grid"):
        p = tables.points(spark, sf, name).agg(F.count("*").alias("n"), F.count_distinct("obj_id").alias("k")).first()
        assert (p.n, p.k) == (n, n)


def test_neighbours_and_densities_of_copies_and_ties_equal_brute_force(spark):
    rng = np.random.default_rng(5)
    x = np.vstack([rng.random((60, 5)), np.repeat(rng.random((2, 5)), 70, axis=0), rng.integers(0, 3, (80, 5)) / 2.0])
    ids = rng.permutation(len(x)) * 3
    d2 = np.zeros((len(x), len(x)))
    for c in range(5):
        d2 += (x[:, c][:, None] - x[:, c][None, :]) ** 2
    df = spark.createDataFrame(list(zip(ids.tolist(), x.tolist(), strict=True)), "obj_id long, x array<double>")
    others = [[j for j in range(len(x)) if j != i] for i in range(len(x))]
    want = sorted((int(ids[i]), int(ids[j])) for i in range(len(x)) for j in sorted(others[i], key=lambda j: (d2[i, j], ids[j]))[:10])
    plan = map_frames.knn(df, 10, 3)
    assert sorted((r.obj_id, r.nbr_id) for r in plan.collect()) == want
    assert "NestedLoopJoin" not in plan._jdf.queryExecution().toString() and "FlatMapCoGroupsInArrow" in plan._jdf.queryExecution().toString()
    rho = {int(ids[i]): sum(d2[i, j] < 0.5 for j in others[i]) for i in range(len(x))}
    got = map_frames.within(df, 0.5, 3)
    assert {r.obj_id: r.rho for r in got.collect()} == rho
    up = {}
    for i in range(len(x)):
        a = int(ids[i])
        above = [(d2[i, j], int(ids[j])) for j in others[i] if (-rho[int(ids[j])], int(ids[j])) < (-rho[a], a)]
        if above:
            up[a] = min(above)
    assert {r.obj_id: (r.d2, r.parent) for r in map_frames.nearest_denser(df, got, 3).collect()} == up
