"""Intermediate tables below the folder that the cluster names in ``spark.checkpoint.dir``."""

from __future__ import annotations

import atexit
import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

ROOT = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))


def workers_import(spark: SparkSession) -> None:
    """Python workers import this package by name, whatever folder the driver was started in."""
    env = spark.sparkContext.environment
    if ROOT not in (paths := env.get("PYTHONPATH", "").split(os.pathsep)):
        env["PYTHONPATH"] = os.pathsep.join([ROOT, *filter(None, paths)])


def scratch(spark: SparkSession, name: str) -> str:
    """A new URI there, removed when the driver ends; a temporary folder of this machine only on a local master."""
    workers_import(spark)
    conf = spark.sparkContext.getConf()
    top = spark.conf.get("spark.checkpoint.dir", None) or conf.get("spark.checkpoint.dir")
    if not top:
        known = spark.sparkContext._jsc.sc().getCheckpointDir()
        if known.isDefined():
            top = known.get()
        elif spark.sparkContext.master.startswith("local") and not spark.sparkContext.master.startswith("local-cluster"):
            top = "file://" + _own_folder()
        else:
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    uri = f"{top.rstrip('/')}/{name}-{uuid.uuid4().hex[:12]}"
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(uri)
    atexit.register(_remove, path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), path)
    return uri


_OWN: list[str] = []


def _own_folder() -> str:
    if not _OWN:
        _OWN.append(tempfile.mkdtemp(prefix="tilt-"))
    return _OWN[0]


def _remove(files, path) -> None:
    try:
        files.delete(path, True)
    except Exception:  # noqa: BLE001  the JVM may have ended before
        return


def written(df: DataFrame, name: str) -> DataFrame:
    """``df`` written once and read again: cuts lineage, and survives lost executors."""
    uri = scratch(df.sparkSession, name)
    df.write.parquet(uri)
    return df.sparkSession.read.schema(df.schema).parquet(uri)
