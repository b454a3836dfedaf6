"""The given Parquet tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One table of a scale-factor folder; the path may be any that Spark can read."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
