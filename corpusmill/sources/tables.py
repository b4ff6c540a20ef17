"""The given tables as DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

NAMES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One table; columns and filters chosen later reach the Parquet scan."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
