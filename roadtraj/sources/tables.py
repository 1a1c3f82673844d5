"""Scans of the given tables, and views for SQL use."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A table, with only ``columns`` read if any are named."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def micros(column: str):
    """Microseconds since 1970 of a zone-less timestamp, read as UTC whatever the session's zone."""
    c = F.col(column)
    return F.timestamp_diff("MICROSECOND", F.expr("timestamp_ntz'1970-01-01 00:00:00'"), c.cast("timestamp_ntz"))


def register_views(spark: SparkSession, sf_dir: str, *names: str) -> None:
    """Temporary views of the tables under their own names."""
    for name in names or TABLES:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def read_gps_text(spark: SparkSession, path: str, kind: str = "csv") -> DataFrame:
    """Location samples from CSV or JSON lines with a fixed schema: trip_id, seq, x, y, t."""
    reader = spark.read.schema("trip_id long, seq int, x double, y double, t long")
    return reader.option("header", True).csv(path) if kind == "csv" else reader.json(path)
