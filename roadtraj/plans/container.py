"""The packed table: what is stored of a trip, and how it is written for pruning."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def packed_table(encoded: DataFrame, temporal: DataFrame, placed: DataFrame) -> DataFrame:
    """trip_id, bits, n_bits, temporal, t_first, t_last and the trip's box."""
    box = placed.groupBy("trip_id").agg(F.min("x0").alias("x0"), F.min("y0").alias("y0"), F.max("x1").alias("x1"), F.max("y1").alias("y1"))
    times = temporal.select("trip_id", "temporal", F.col("temporal")[0]["t"].alias("t_first"), F.element_at("temporal", -1)["t"].alias("t_last"))
    return encoded.select("trip_id", "bits", "n_bits").join(times, "trip_id").join(box, "trip_id", "left")


def write_packed(packed: DataFrame, path: str, partitions: int) -> None:
    """Files sorted by first time, so that row groups prune on time and box; one shuffle by time ranges."""
    packed.repartitionByRange(partitions, "t_first").sortWithinPartitions("t_first").write.mode("overwrite").option("compression", "zstd").parquet(path)


def write_bucketed(packed: DataFrame, table: str, buckets: int) -> None:
    """A table bucketed by trip, for joins by trip without a shuffle."""
    packed.write.mode("overwrite").bucketBy(buckets, "trip_id").sortBy("trip_id").saveAsTable(table)


def read_packed(spark, path: str, t1: int | None = None, t2: int | None = None) -> DataFrame:
    """Packed trips under way between two times; the filter reaches the Parquet scan."""
    df = spark.read.parquet(path)
    df = df if t2 is None else df.where(F.col("t_first") <= t2)
    return df if t1 is None else df.where(F.col("t_last") >= t1)
