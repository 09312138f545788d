"""Session helpers shared by the library: shipping the package, checkpoints, table paths."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

ROOT = Path(__file__).resolve().parent


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; only Spark opens the path, so any store it knows will do."""
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def ship_package(spark: SparkSession) -> None:
    """Make this package importable in Python workers that don't have the repository on their path."""
    sc = spark.sparkContext
    if sc.master.split("[")[0] == "local" or getattr(sc, "_corridor_shipped", False):
        return  # workers of a local session run on this machine, under the driver's path
    target = os.path.join(tempfile.mkdtemp(), "corridor_package.zip")
    with zipfile.ZipFile(target, "w") as z:
        for p in ROOT.rglob("*"):
            if p.is_file() and "__pycache__" not in p.parts:
                z.write(p, p.relative_to(ROOT.parent))
    sc.addPyFile(target)
    sc._corridor_shipped = True


def checkpoint_dir(spark: SparkSession) -> None:
    """Use the cluster's shared checkpoint folder; set one of our own only where none is named."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="corridor-checkpoint-"))


def cut(df: DataFrame) -> DataFrame:
    """Materialise a frame in the checkpoint folder and forget its lineage."""
    checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def scratch(spark: SparkSession, name: str) -> str:
    """A new folder's path in the checkpoint folder, which all executors see."""
    checkpoint_dir(spark)
    return f"{spark.sparkContext.getCheckpointDir()}/{name}-{uuid.uuid4().hex}"


def remove(spark: SparkSession, path: str) -> None:
    """Delete a folder of our own on whatever file system it lies."""
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    at = jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(conf).delete(at, True)
