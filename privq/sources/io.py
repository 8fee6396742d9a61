"""Scans, sinks and samples."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A Parquet table; naming columns keeps the scan to them."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read(spark: SparkSession, path: str, kind: str, schema: str | T.StructType, **options: str) -> DataFrame:
    """CSV, JSON, ORC or Parquet under a declared schema (nothing is inferred)."""
    if kind not in ("csv", "json", "orc", "parquet"):
        raise ValueError("kind must be csv, json, orc or parquet")
    return spark.read.schema(schema).options(**options).format(kind).load(path)


def stream(spark: SparkSession, path: str, schema: T.StructType, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def write_release(released: DataFrame, path: str, **tags: str | float) -> None:
    """Append a release with its public tags, partitioned by method if there is one."""
    tagged = released.withColumns({k: F.lit(v) for k, v in tags.items()})
    writer = tagged.write.mode("append")
    (writer.partitionBy("method") if "method" in tags else writer).parquet(path)


def write_index(index: DataFrame, path: str, parts: int = 64) -> None:
    """A rank index sorted for range lookups: files cover ranges of values, row groups prune by their bounds."""
    index.repartitionByRange(parts, "value").sortWithinPartitions("value").write.parquet(path)


def sample(df: DataFrame, fraction: float, seed: int = 7) -> DataFrame:
    """Row sample for splitters only: it speeds up, and never feeds released ranks or lowers a privacy cost."""
    return df.sample(fraction=fraction, seed=seed)


def literals(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)
