"""Shared scratch space: where a cut of the lineage is written.

Executors come and go, so nothing is kept in executor memory or on an executor's own disk. A cut is a Parquet folder
below ``spark.checkpoint.dir``, which the cluster shares. Only a local session without that setting (tests on one
machine) gets a temporary folder; a cluster without it is an error.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_fallback: dict[str, str] = {}


def shared_root(spark: SparkSession) -> str:
    """The folder all executors share; a machine-local one only where the session is local and names none."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    if not spark.sparkContext.master.split("[")[0] == "local":
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if "root" not in _fallback:
        _fallback["root"] = tempfile.mkdtemp(prefix="privq-")
    return "file://" + _fallback["root"]


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` once to the shared folder and read it back with the same schema."""
    return Scratch(df.sparkSession).store(df, name)


def delete_path(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


class Scratch:
    """The stored steps of one operator; ``clear`` deletes those that its result doesn't read."""

    def __init__(self, spark: SparkSession):
        self.spark = spark
        self.paths: list[str] = []

    def store(self, df: DataFrame, name: str) -> DataFrame:
        path = fresh_path(self.spark, name)
        df.write.parquet(path)
        self.paths.append(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop_last(self) -> None:
        """Delete the step stored last."""
        delete_path(self.spark, self.paths.pop())

    def clear(self) -> None:
        while self.paths:
            self.drop_last()
