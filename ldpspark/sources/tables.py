"""The given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .ship import ship

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name not in TABLES:
        raise ValueError(f"no table {name}")
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register(spark: SparkSession, sf_dir: str, prefix: str = "") -> None:
    """Temporary views of all tables that are there."""
    for name in TABLES:
        load(spark, sf_dir, name).createOrReplaceTempView(prefix + name)
