"""Readers and writers around the search."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read(spark: SparkSession, path: str, format: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    reader = spark.read.format(format).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def write_mps(mps: DataFrame, path: str) -> None:
    mps.write.mode("overwrite").partitionBy("target").parquet(path)


def resume(spark: SparkSession, path: str) -> DataFrame:
    """Parent sets written by `write_mps`."""
    return spark.read.parquet(path).select("target", "parents", "size", "score")


def write_scores(mps: DataFrame, path: str) -> None:
    """Interchange text for exact network solvers: a line per set, `target score size parents`."""
    line = F.concat_ws(" ", "target", F.format_string("%.6f", "score"), F.col("size").cast("string"), F.array_join("parents", " "))
    mps.sort("target", "score").select(line.alias("value")).write.mode("overwrite").text(path)
