"""Interval joins as equi-joins on buckets.

Spark joins ``value between lo and hi`` by comparing every pair. Here each
interval is put into the buckets that it touches and each value into its own, so
the join is hashed on (key, bucket) and the interval test is a residual filter.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def interval_join(values: DataFrame, intervals: DataFrame, keys: list[str], value: str, lo: str, hi: str, width: int) -> DataFrame:
    """Rows of both sides where keys are equal and lo <= value < hi; ``width`` is about an interval's length."""
    left = values.withColumn("_bucket", F.floor(F.col(value) / width).cast("long"))
    touched = F.sequence(F.floor(F.col(lo) / width).cast("long"), F.floor((F.greatest(F.col(hi) - 1, F.col(lo))) / width).cast("long"))
    right = intervals.withColumn("_bucket", F.explode(touched))
    return left.join(right, [*keys, "_bucket"]).where((F.col(lo) <= F.col(value)) & (F.col(value) < F.col(hi))).drop("_bucket")


def asof_join(left: DataFrame, right: DataFrame, keys: list[str], time: str, columns: list[str]) -> DataFrame:
    """``left`` with ``columns`` of the last row of ``right`` at or before its time: a union, one sort, no pairs."""
    from pyspark.sql import Window

    marked = left.withColumns({"_side": F.lit(1), **{c: F.lit(None).cast(right.schema[c].dataType) for c in columns}})
    source = right.select(*keys, time, *columns).withColumns({"_side": F.lit(0), **{c: F.lit(None).cast(left.schema[c].dataType) for c in left.columns if c not in (*keys, time)}})
    by = Window.partitionBy(*keys).orderBy(time, "_side").rowsBetween(Window.unboundedPreceding, 0)
    filled = marked.unionByName(source).withColumns({c: F.last(F.when(F.col("_side") == 0, F.struct(c)), ignorenulls=True).over(by)[c] for c in columns})
    return filled.where("_side = 1").drop("_side")
