"""Clustering a stream of chunks with Structured Streaming.

Each micro-batch reads the newest map version, clusters its chunks in order and
writes assignments, neurons and edges under its batch id. A batch that is run
again overwrites its own output and starts from the version before it, so a
restart changes nothing.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.growing_map import GrowingMap
from ..params import Params
from ..plans import pipeline


def load_map(spark: SparkSession, folder: str, before: int) -> GrowingMap | None:
    """The newest version below ``before``, or None."""
    try:
        versions = spark.read.parquet(f"{folder}/neurons").where(F.col("version") < before)
        newest = versions.agg(F.max("version")).first()[0]
    except Exception as e:  # no version has been written yet
        if "PATH_NOT_FOUND" in str(e) or "UNABLE_TO_INFER_SCHEMA" in str(e):
            return None
        raise
    if newest is None:
        return None
    rows = [r.asDict() for r in versions.where(F.col("version") == newest).collect()]
    edges = [r.asDict() for r in spark.read.parquet(f"{folder}/edges").where(F.col("version") == newest).collect()]
    return GrowingMap.from_rows(rows, edges, len(rows[0]["w"]))


def save_map(spark: SparkSession, folder: str, version: int, m: GrowingMap) -> None:
    rows = [(i, int(m.subnet[i]), m.w[i].tolist(), float(m.strain[i]), int(m.hits[i])) for i in range(m.q)]
    spark.createDataFrame(rows, "neuron int, subnet int, w array<double>, strain double, hits long").coalesce(1).write.mode("overwrite").parquet(f"{folder}/neurons/version={version}")
    spark.createDataFrame(m.edges(), "a int, b int").coalesce(1).write.mode("overwrite").parquet(f"{folder}/edges/version={version}")


def on_batch(folder: str, p: Params):
    """A foreachBatch function over points (chunk_id, obj_id, x)."""

    def run(batch: DataFrame, epoch: int) -> None:
        spark = batch.sparkSession
        state = load_map(spark, folder, epoch)
        parts = []
        # One batch is a bounded number of chunks; each is at most a task's rows.
        for (chunk,) in batch.select("chunk_id").distinct().orderBy("chunk_id").collect():
            part = batch.where(F.col("chunk_id") == chunk).select("chunk_id", "obj_id", "x").limit(p.max_rows_per_task + 1).toPandas()
            if len(part) > p.max_rows_per_task:
                raise ValueError("a chunk outgrows a task: use narrower windows or cluster_sharded")
            part = part.sort_values("obj_id", kind="stable")
            f = pipeline.fit_chunk(np.array(part["x"].to_list(), float), p, state if p.carry == "warm" else None)
            state = f.map
            parts.append(part[["chunk_id", "obj_id"]].assign(cluster=f.labels.astype(np.int32)))
        if parts:
            spark.createDataFrame(pd.concat(parts), "chunk_id long, obj_id long, cluster int").write.mode("overwrite").parquet(f"{folder}/assignments/epoch={epoch}")
            save_map(spark, folder, epoch, state)

    return run


def start(points: DataFrame, folder: str, p: Params = Params(carry="warm"), once: bool = True):
    """Start the query over a streaming DataFrame of points."""
    writer = points.writeStream.foreachBatch(on_batch(folder, p)).option("checkpointLocation", f"{folder}/checkpoint")
    return (writer.trigger(availableNow=True) if once else writer.trigger(processingTime="1 minute")).start()


def keyed_maps(points: DataFrame, p: Params = Params()):
    """Many streams side by side: a map in each stream_key's state, trained on
    every batch; returns a streaming DataFrame of (stream_key, version, q, n)."""
    from pyspark.sql.streaming.state import GroupStateTimeout

    import pickle

    def update(key, parts, state):
        version, raw = state.get if state.exists else (0, None)
        m = pickle.loads(raw) if raw else None
        x = [np.array(part.sort_values("obj_id")["x"].to_list(), float) for part in parts]
        x = np.vstack([v for v in x if len(v)])
        from ..operators import growing_map

        m = growing_map.fit(x, p, m)
        state.update((version + 1, pickle.dumps(m)))
        yield pd.DataFrame({"stream_key": [key[0]], "version": [version + 1], "q": [m.q], "n": [len(x)]})

    return points.groupBy("stream_key").applyInPandasWithState(update, "stream_key string, version long, q long, n long", "version long, map binary", "update", GroupStateTimeout.NoTimeout)


def windowed_counts(events: DataFrame, late: str = "1 hour", width: str = "14 hours 24 minutes", start_: str = "9 hours 36 minutes") -> DataFrame:
    """Rows and mean value by window and type, late rows dropped after the watermark."""
    w = F.window("ts", width, width, start_)
    return events.withWatermark("ts", late).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.avg("value").alias("mean")).select(F.unix_timestamp("w.start").alias("chunk_id"), "event_type", "n", "mean")
