"""Readers of the given tables and of edge lists in common formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", a: str = "a", b: str = "b") -> DataFrame:
    """(a, b) pairs from parquet, orc, json, csv (with a header) or text (two
    ids per line, blanks between, lines with # left out)."""
    if fmt == "text":
        line = spark.read.text(path).filter(~F.col("value").startswith("#"))
        parts = F.split(F.trim("value"), r"\s+")
        return line.select(parts[0].alias("a"), parts[1].alias("b"))
    reader = spark.read.option("header", True) if fmt == "csv" else spark.read
    return reader.format(fmt).load(path).select(F.col(a).alias("a"), F.col(b).alias("b"))


def write_bucketed(df: DataFrame, name: str, buckets: int, key: str) -> None:
    """A table bucketed and sorted by one column, for joins without a shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)
