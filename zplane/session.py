"""Session helpers shared by every operator: worker imports, the shared folder, lineage cuts."""

from __future__ import annotations

import os
import re
import uuid

from pyspark.sql import DataFrame, SparkSession

_ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def ship(spark: SparkSession) -> None:
    """Let Python workers import this package from the place the driver has it.

    On a cluster install the package on the executors (or pass it with --py-files); where the
    repository lies at the same path on every machine this is enough.
    """
    env = spark.sparkContext.environment
    seen = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
    if _ROOT not in seen:
        env["PYTHONPATH"] = os.pathsep.join([_ROOT, *seen])


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or on one machine our own if that is unset."""
    known = spark.conf.get("spark.checkpoint.dir", None)
    if known:
        return known.rstrip("/")
    master = spark.sparkContext.master
    if not re.fullmatch(r"local(\[[^-\]]*\])?", master):
        raise ValueError(f"set spark.checkpoint.dir to a folder that driver and executors of {master} share")
    own = "/tmp/zplane-checkpoints"
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(own)
    return own


def checkpoint(df: DataFrame) -> DataFrame:
    """Cut the lineage with a reliable checkpoint in the shared folder."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def stored(df: DataFrame, name: str = "table") -> DataFrame:
    """Write df as parquet in the shared folder and read it back (columnar, compressed, re-readable)."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/zplane/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def discard(spark: SparkSession, df: DataFrame) -> None:
    """Delete what stored() wrote for df, once nothing reads it any more."""
    jvm = spark.sparkContext._jvm
    conf = spark.sparkContext._jsc.hadoopConfiguration()
    for f in df.inputFiles()[:1]:
        path = jvm.org.apache.hadoop.fs.Path(f).getParent()
        if "/zplane/" in path.toString():
            path.getFileSystem(conf).delete(path, True)


def estimated_bytes(df: DataFrame) -> int:
    """What Spark's optimiser expects df to hold (files as stored); a table of unknown size counts 128 MB for each partition."""
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return size if size < 1 << 60 else df.rdd.getNumPartitions() << 27


def release(spark: SparkSession) -> None:
    """Let the driver drop what it no longer refers to, so that Spark deletes finished shuffles' files.

    Their cleanup otherwise waits for a garbage collection of the driver, which may not come before a
    long job ends.
    """
    import gc

    gc.collect()
    spark.sparkContext._jvm.System.gc()


_KEPT: dict = {}


def worker_cache(key, make=None):
    """The one object that a Python worker keeps between tasks: asking for another key (or None) drops it.

    Workers live on and serve all operators, so whatever each of them kept would add up.
    """
    old = [k for k in _KEPT if k != key]
    for k in old:
        del _KEPT[k]
    if old:
        trim()
    if key is not None and key not in _KEPT:
        _KEPT[key] = make()
    return _KEPT.get(key)


def trim() -> None:
    """Give freed memory of this process back to the system (where the C library can)."""
    import ctypes
    import gc

    gc.collect()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):
        return


def clear_shared(spark: SparkSession) -> None:
    """Delete all tables that stored() has written in the shared folder; for use once their results are consumed."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{shared_dir(spark)}/zplane")
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
