"""Parquet sources with declared schemas, and partitioned sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..schema import TABLES


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables."""
    reader = spark.read
    return (reader.schema(TABLES[name]) if name in TABLES else reader).parquet(f"{sf_dir}/{name}.parquet")


def write_result(df: DataFrame, path: str, mode: str = "overwrite") -> None:
    """Results by series, so that a later read of some series touches only theirs."""
    df.repartition("series_id").write.mode(mode).partitionBy("series_id").parquet(path)
