"""What the operators need from the running session."""

from __future__ import annotations

import contextlib
import os
import uuid

from pyspark.sql import DataFrame, SparkSession

#: Folder for intermediate tables where the session names none (tests on one machine).
LOCAL_SHARED_DIR = "file:///tmp/checkpoints/spectral_ridge"


def ship_package(spark: SparkSession) -> None:
    """Let Python workers import this package from the place the driver imports it from."""
    with contextlib.suppress(AttributeError):
        root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
        paths = spark.sparkContext.environment.get("PYTHONPATH", "")
        if root not in paths.split(os.pathsep):
            spark.sparkContext.environment["PYTHONPATH"] = os.pathsep.join(p for p in (root, paths) if p)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir`` where it is set. Only a
    session on one machine may leave it unset."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not named and not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    return (named or LOCAL_SHARED_DIR).rstrip("/")


def materialise(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` once to the shared folder and read it back: lineage ends here."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)
