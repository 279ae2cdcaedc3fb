"""Functions for SQL users: register(spark) makes them available by name."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators import merging
from ..params import Params


@F.pandas_udf(T.DoubleType())
def gap_log(n_i: pd.Series, v_i: pd.Series, n_j: pd.Series, v_j: pd.Series) -> pd.Series:
    """Log density gap of two clusters from counts and variances on their line."""
    return pd.Series([-float(merging.log_mixture(a, b, c, d).min()) for a, b, c, d in zip(n_i, v_i, n_j, v_j, strict=True)])


@F.pandas_udf(T.DoubleType())
def vec_dist(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([float(np.linalg.norm(np.asarray(p) - np.asarray(q))) for p, q in zip(a, b, strict=True)])


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def vec_mean(x: pd.Series) -> list:
    """Aggregate: mean vector of a group."""
    return np.mean(np.array(x.to_list()), axis=0).tolist()


@F.udtf(returnType=T.StructType([T.StructField("step", T.IntegerType()), T.StructField("u", T.DoubleType()), T.StructField("log_m", T.DoubleType())]))
class GapCurve:
    """gap_curve(n_i, v_i, n_j, v_j): the log mixture density at 101 places."""

    def eval(self, n_i: float, v_i: float, n_j: float, v_j: float):
        for step, (u, m) in enumerate(zip(merging.GRID, merging.log_mixture(n_i, v_i, n_j, v_j), strict=True)):
            yield step - 50, float(u), float(m)


@F.udtf(returnType=T.StructType([T.StructField("obj_id", T.LongType()), T.StructField("cluster", T.IntegerType())]))
class ClusterChunk:
    """cluster_chunk(TABLE t): the whole method on a chunk of (obj_id, x)."""

    def __init__(self):
        self.ids, self.x = [], []

    def eval(self, row):
        self.ids.append(row["obj_id"])
        self.x.append(row["x"])

    def terminate(self):
        from ..plans.pipeline import fit_chunk

        order = np.argsort(self.ids, kind="stable")
        x = np.array(self.x, float)[order]
        for i, c in zip(np.array(self.ids)[order], fit_chunk(x, Params()).labels, strict=True):
            yield int(i), int(c)


def register(spark: SparkSession) -> None:
    spark.udf.register("gap_log", gap_log)
    spark.udf.register("vec_dist", vec_dist)
    spark.udf.register("vec_mean", vec_mean)
    spark.udtf.register("gap_curve", GapCurve)
    spark.udtf.register("cluster_chunk", ClusterChunk)


