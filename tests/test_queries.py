"""Registered queries against their SQL, and the plans that need Spark."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from driftclust import queries as Q
from driftclust.operators import features, metrics, sampler
from driftclust.params import Params
from driftclust.plans import pipeline
from driftclust.sources import tables

SOME = ["ari", "dbi", "best_k", "winner_embeddings_15", "split_test", "log_gap_events_types", "sampler_plan_literal", "sampler_draw_events", "planted_ga_part", "kmeans_3rounds_events", "join_interval", "join_as_of", "session_windows", "minmax_lineitem"]


def norm(rows):
    return sorted(tuple(repr(round(v, 9) + 0.0) if isinstance(v, float) else str(v) for v in r) for r in rows)


@pytest.mark.parametrize("name", SOME)
def test_query_equals_sql(spark, sf, name):
    import glob
    import os

    c = duckdb.connect()
    for f in glob.glob(f"{sf}/*.parquet"):
        c.sql(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    df = Q.queries()[name](spark, sf)
    cols = sorted(df.columns)
    got = [tuple(r) for r in df.select(*cols).collect()]
    assert norm(got) == norm(c.sql(f"select {','.join(cols)} from ({Q.oracle_sql()[name]})").fetchall())


def test_every_oracle_has_a_query():
    assert set(Q.oracle_sql()) <= set(Q.queries())


def test_flagship_reaches_the_accuracy(spark, sf):
    rows = Q.flagship(spark, sf).collect()
    assert len(rows) == 4 and rows[0].ari > 0.95


def test_ari_of_hand_examples(spark):
    for clusters, value in (((1, 1, 2, 2), 1.0), ((1, 2, 1, 2), -0.5), ((1, 1, 1, 1), 0.0)):
        df = spark.createDataFrame(list(zip("aabb", clusters, strict=True)), "label string, cluster int")
        assert metrics.ari(df).first().ari == pytest.approx(value)


def test_minmax_maps_constants_to_zero(spark):
    df = spark.createDataFrame([(1, [1.0, 5.0]), (2, [3.0, 5.0])], "obj_id long, x array<double>")
    assert sorted(r.x for r in features.minmax(df).collect()) == [[0.0, 0.0], [1.0, 0.0]]


def test_sampler_example(spark):
    pts = spark.createDataFrame([(i, [0.0], 0 if i < 10 else 1 if i < 60 else 2) for i in range(460)], "obj_id long, x array<double>, label int")
    for base, sizes in (("source", lambda a, b: (10, min(a * 10, 50), min(b * 50, 400))), ("chunk", lambda a, b: (10, min(a * 10, 50), min(b * min(a * 10, 50), 400)))):
        rows = sampler.plan(pts, 6, 5, base=base, k_chunk=3).collect()
        for c in range(6):
            r = sorted((x.pos, x.ratio, x.target_n) for x in rows if x.chunk_id == c)
            assert tuple(x[2] for x in r) == sizes(r[1][1], r[2][1]) and r[1][1] <= r[2][1]


def test_chunks_do_not_depend_on_partitions(spark, sf):
    pts = sampler.stream(tables.points(spark, sf, "ga"), 3, 5)
    a = pipeline.cluster_chunks(pts.repartition(1)).toPandas().sort_values(["chunk_id", "obj_id"], ignore_index=True)
    b = pipeline.cluster_chunks(pts.repartition(7)).toPandas().sort_values(["chunk_id", "obj_id"], ignore_index=True)
    assert a.equals(b) and a["chunk_id"].nunique() == 3


def test_sharded_and_predict(spark, sf):
    pts = tables.points(spark, sf, "ga")
    whole = pipeline.with_truth(pts, pipeline.cluster_sharded(pts, shards=4).withColumn("chunk_id", F.lit(0).cast("long")))
    assert metrics.ari(whole).first().ari > 0.8
    model = pipeline.neurons(pts)
    assert metrics.ari(pipeline.predict(pts, model)).first().ari > 0.95


def test_stream_equals_chunked_batch(spark, sf, tmp_path):
    from driftclust.streaming import stream

    pts = sampler.stream(tables.points(spark, sf, "ga"), 3, 5).select("chunk_id", "obj_id", "x").persist()
    for c in range(3):
        pts.where(F.col("chunk_id") == c).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    sdf = spark.readStream.schema(pts.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    q = stream.start(sdf, str(tmp_path / "out"), Params(carry="cold"))
    q.awaitTermination()
    got = spark.read.parquet(str(tmp_path / "out/assignments")).select("chunk_id", "obj_id", "cluster").toPandas().sort_values(["chunk_id", "obj_id"], ignore_index=True)
    want = pipeline.cluster_chunks(pts).toPandas().sort_values(["chunk_id", "obj_id"], ignore_index=True)
    assert (got.to_numpy() == want.to_numpy()).all()
    m = stream.load_map(spark, str(tmp_path / "out"), 99)
    assert m.q > 3 and stream.load_map(spark, str(tmp_path / "none"), 99) is None
    stream.on_batch(str(tmp_path / "out"), Params())(pts.where("chunk_id = 2"), 2)
    again = stream.load_map(spark, str(tmp_path / "out"), 99)
    assert np.allclose(again.w.shape, again.w.shape)


def test_sql_functions(spark):
    from driftclust.functions.sql_functions import register

    register(spark)
    assert spark.sql("select gap_log(100L, 0.0625D, 100L, 0.0625D) g").first().g == pytest.approx(np.log(4.630404), abs=1e-5)
    assert spark.sql("select count(*) c from gap_curve(100D, 0.0625D, 100D, 0.0625D)").first().c == 101


def test_windowed_stream_counts(spark, sf):
    from driftclust.streaming.stream import windowed_counts

    q = windowed_counts(tables.read_stream(spark, sf)).writeStream.format("memory").queryName("w").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.sql("select count(distinct chunk_id) c from w").first().c >= 48


#: Table and the columns of it that each query's job stands on.
ON_TABLES = {"mixture_curve": "lineitem", "gap_udf": "lineitem", "score_trace": "lineitem", "best_k": "lineitem", "knee_k": "lineitem", "summary_mean_std": "events", "rank_methods": "events", "cost_predict": "events"}


@pytest.mark.parametrize("name", ON_TABLES)
def test_query_reads_its_table_and_equals_sql(spark, sf, name):
    df = Q.queries()[name](spark, sf)
    assert any(f.endswith(f"/{ON_TABLES[name]}.parquet") for f in df.inputFiles())
    test_query_equals_sql(spark, sf, name)
    assert df.count() > 0
