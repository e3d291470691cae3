"""Readers of the given tables and of series in other formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SERIES_SCHEMA = "var string, step int, pos bigint, value double"


def load_table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_series(spark: SparkSession, path: str, fmt: str = "parquet", **options: str) -> DataFrame:
    """A series stored as (var, step, pos, value) in any built-in format; the schema is declared, not inferred."""
    return spark.read.format(fmt).schema(SERIES_SCHEMA).options(**options).load(path)
