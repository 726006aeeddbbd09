"""Reading the given Parquet tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One table of a data directory; any URI that Spark can read."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
