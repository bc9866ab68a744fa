"""Shared-folder storage: where intermediate tables go and how they are written."""

from __future__ import annotations

import os
import posixpath
import tempfile
import uuid
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_ROOT = str(Path(__file__).resolve().parents[2])


def shared_dir(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; a temporary one only in single-JVM tests."""
    sc = spark.sparkContext
    set_to = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if set_to:
        return set_to
    if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    sc.setCheckpointDir(made := tempfile.mkdtemp(prefix="rangeknn_"))
    return made


def new_path(spark: SparkSession, name: str) -> str:
    return posixpath.join(shared_dir(spark), "rangeknn", uuid.uuid4().hex, name)


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write df to the shared folder and read it back: lineage is cut, executors may be lost."""
    spark = df.sparkSession
    df.write.option("compression", "zstd").parquet(path := new_path(spark, name))
    back = spark.read.schema(df.schema).parquet(path)
    back.stored_at = path
    return back


def discard(df: DataFrame) -> None:
    """Delete a materialised table that nothing reads any more."""
    spark = df.sparkSession
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(df.stored_at)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def release(spark: SparkSession) -> None:
    """Let Spark's cleaner drop the shuffle files of plans that nothing refers to any more."""
    import gc

    gc.collect()
    spark.sparkContext._jvm.System.gc()


def workers_import(spark: SparkSession) -> None:
    """Python workers find this package where the driver found it (same path on every node)."""
    env = spark.sparkContext.environment
    if _ROOT not in env.get("PYTHONPATH", "").split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (_ROOT, env.get("PYTHONPATH", "")) if x)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    workers_import(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
