"""Readers and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read_table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def read_slots(spark: SparkSession, path: str, format_: str = "parquet", schema: str = "series_id string, slot bigint, value double", **options) -> DataFrame:
    """Readings from Parquet, ORC, JSON or CSV with a declared schema; NaN becomes a gap."""
    df = spark.read.schema(schema).options(**options).format(format_).load(path)
    return df.withColumn("value", F.when(~F.isnan("value"), F.col("value")))


def write_windows(df: DataFrame, path: str, format_: str = "parquet", mode: str = "overwrite") -> None:
    """Windows partitioned by completeness, so training reads only the complete part."""
    df.write.mode(mode).partitionBy("complete").format(format_).save(path)


def read_windows(spark: SparkSession, path: str, complete: bool, format_: str = "parquet") -> DataFrame:
    """One side of what ``write_windows`` wrote, from its own partition."""
    return spark.read.format(format_).load(path).where(F.col("complete") == F.lit(str(complete).lower())).withColumn("complete", F.lit(complete))
