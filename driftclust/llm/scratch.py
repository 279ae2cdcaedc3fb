"""Shared folder for intermediate tables, and worker set-up.

Intermediate results that several jobs read are written as Parquet below the
folder named by ``spark.checkpoint.dir``, which the driver and all executors
share; a lost executor then costs a re-read, never a lost result.
"""

from __future__ import annotations

import ctypes
import functools
import gc
import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

#: Rows of an Arrow batch at most.
BATCH_ROWS = 1000
REPO = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))


def prepare(spark: SparkSession) -> None:
    """Let Python workers import this package when it isn't installed, and keep
    the batches of whole texts that they and the JVM hold small."""
    env = spark.sparkContext.environment
    paths = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
    if REPO not in paths:
        env["PYTHONPATH"] = os.pathsep.join([*paths, REPO])
    # Workers give freed memory back; else each keeps what its largest batch took.
    for name, value in (("TOKENIZERS_PARALLELISM", "false"), ("ARROW_DEFAULT_MEMORY_POOL", "system"), ("MALLOC_ARENA_MAX", "2"), ("MALLOC_TRIM_THRESHOLD_", "4194304"), ("MALLOC_MMAP_THRESHOLD_", "1048576")):
        env.setdefault(name, value)
    batch = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(batch)) <= BATCH_ROWS:
        spark.conf.set(batch, BATCH_ROWS)


def lean(task):
    """A task over Arrow batches that hands freed memory back when it ends.

    Spark deals tasks out to all idle workers in turn, so what each still holds
    afterwards adds up over the workers of an executor.
    """

    @functools.wraps(task)
    def run(*batches):
        yield from task(*batches)
        gc.collect()
        if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
            trim(0)

    return run


def shared_dir(spark: SparkSession) -> str:
    """The shared folder as a URI; a temporary one only where none is set."""
    root = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", "")
    if not root:
        root = spark.sparkContext.getCheckpointDir()
    if not root:
        root = "file://" + tempfile.mkdtemp(prefix="driftclust-")
        spark.sparkContext.setCheckpointDir(root)
        root = spark.sparkContext.getCheckpointDir()
    return root.rstrip("/")


def new_dir(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def materialise(df: DataFrame, name: str, compression: str = "snappy") -> DataFrame:
    """Write ``df`` once to the shared folder and read it back; cuts lineage."""
    spark = df.sparkSession
    path = new_dir(spark, name)
    df.write.parquet(path, compression=compression)
    out = spark.read.schema(df.schema).parquet(path)
    out.scratch_path = path
    return out


def release(*frames: DataFrame) -> None:
    """Delete what ``materialise`` wrote for these, and let Spark's cleaner drop
    the shuffle files of plans that nothing refers to any more."""
    for df in frames:
        remove(df.sparkSession, df.scratch_path)
    if frames:
        gc.collect()
        frames[0].sparkSession.sparkContext._jvm.System.gc()


def remove(spark: SparkSession, path: str) -> None:
    """Delete a folder in whatever store holds it."""
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
