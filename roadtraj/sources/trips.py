"""Trips of the given tables: spatial path and temporal sequence apart.

``events`` is a walk on the network: (user, ten-day block) is a trip, a value
class is a turn, an error is a stop. ``orders`` are distance-time curves without
a network; ``lineitem`` orders are tours over supplier vertices; words, roles
and url parts are symbol paths.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from roadtraj.sources.network import build_network, network_size
from roadtraj.sources.tables import load, micros

T_SCALE = 1300


def events_walk(spark: SparkSession, sf_dir: str, kind: str = "nation") -> DataFrame:
    """One row for each event: trip_id, dk, seq, event_id, e (null: stays), off, t."""
    n, wide = network_size(spark, sf_dir, kind)
    high = n // wide
    ev = load(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type", "value").withColumn("us", micros("ts"))
    dk = F.floor((F.col("us") - F.lit(1704067200000000)) / F.lit(864000000000)).cast("int")
    turn = F.when(F.col("event_type") == "error", None).when(F.col("value") < 35, 0).when(F.col("value") < 70, 1).when(F.col("value") < 110, 2).otherwise(3)
    ev = ev.withColumns({"dk": dk, "dir": turn}).withColumn("trip_id", F.col("user_id") * 10 + F.col("dk"))
    by = Window.partitionBy("trip_id").orderBy("us", "event_id")
    before = by.rowsBetween(Window.unboundedPreceding, -1)
    dx, dy = F.when(F.col("dir") == 0, 1).when(F.col("dir") == 2, -1).otherwise(0), F.when(F.col("dir") == 1, 1).when(F.col("dir") == 3, -1).otherwise(0)
    start = F.col("user_id") % n
    moved = ev.withColumns({"seq": F.row_number().over(by), "sx": F.coalesce(F.sum(dx).over(before), F.lit(0)), "sy": F.coalesce(F.sum(dy).over(before), F.lit(0))})
    x, y = F.pmod(start % wide + F.col("sx"), F.lit(wide)), F.pmod(F.floor(start / wide) + F.col("sy"), F.lit(high))
    return moved.select("trip_id", "dk", "seq", "event_id", F.when(F.col("dir").isNotNull(), (y * wide + x) * 4 + F.col("dir")).cast("int").alias("e"), F.floor(F.col("us") / T_SCALE).cast("long").alias("t"))


def trip_steps(spark: SparkSession, sf_dir: str, kind: str = "nation") -> DataFrame:
    """trip_id, train, pos, e: the edges driven."""
    by = Window.partitionBy("trip_id").orderBy("seq")
    return events_walk(spark, sf_dir, kind).where("e IS NOT NULL").select("trip_id", (F.col("dk") == 0).alias("train"), F.row_number().over(by).alias("pos"), "e")


def as_paths(steps: DataFrame) -> DataFrame:
    """trip_id, train, path: one row for each trip."""
    return steps.groupBy("trip_id", "train").agg(F.sort_array(F.collect_list(F.struct("pos", "e"))).alias("s")).select("trip_id", "train", F.col("s.e").alias("path"))


def trip_paths(spark: SparkSession, sf_dir: str, kind: str = "nation") -> DataFrame:
    return as_paths(trip_steps(spark, sf_dir, kind))


def trip_points(spark: SparkSession, sf_dir: str, kind: str = "nation") -> DataFrame:
    """trip_id, seq, d, t: distance travelled at each sample; a stop repeats it."""
    walk = events_walk(spark, sf_dir, kind).join(F.broadcast(build_network(spark, sf_dir, kind).select("e", "w")) if kind == "nation" else build_network(spark, sf_dir, kind).select("e", "w"), "e", "left")
    by = Window.partitionBy("trip_id").orderBy("seq")
    done = F.coalesce(F.sum("w").over(by.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    here = walk.withColumn("d", F.when(F.col("e").isNotNull(), done + F.floor(F.col("w") * (F.col("event_id") % 4 + 1) / 4)))
    return here.select("trip_id", "seq", F.coalesce(F.last("d", ignorenulls=True).over(by.rowsBetween(Window.unboundedPreceding, 0)), F.lit(0)).cast("long").alias("d"), "t")


def as_temporal(points: DataFrame) -> DataFrame:
    """trip_id, temporal: array of (d, t) by time."""
    return points.groupBy("trip_id").agg(F.sort_array(F.collect_list(F.struct("t", "d"))).alias("s")).select("trip_id", F.expr("transform(s, p -> struct(p.d as d, p.t as t))").alias("temporal"))


def trip_temporal(spark: SparkSession, sf_dir: str, kind: str = "nation") -> DataFrame:
    return as_temporal(trip_points(spark, sf_dir, kind))


def money_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """trip_id (customer), seq, d (cents so far), t (day): one point a day."""
    o = load(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_totalprice", "o_orderdate")
    by = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    cents = F.round(F.col("o_totalprice") * 100).cast("long")
    day = F.floor(micros("o_orderdate") / F.lit(86400000000)).cast("long")
    run = o.select(F.col("o_custkey").alias("trip_id"), day.alias("t"), F.sum(cents).over(by).alias("d"))
    daily = run.groupBy("trip_id", "t").agg(F.max("d").alias("d"))
    return daily.select("trip_id", F.row_number().over(Window.partitionBy("trip_id").orderBy("t")).alias("seq"), "d", "t")


def tour_stops(spark: SparkSession, sf_dir: str, each: bool = False) -> DataFrame:
    """trip_id (order), stop, v, day: supplier vertices in shipping order, one for each day or ``each`` line item, equal neighbours once."""
    n, _ = network_size(spark, sf_dir, "supplier")
    rows = load(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_suppkey", "l_partkey", "l_extendedprice", "l_shipdate")
    place = F.struct("l_linenumber", "l_suppkey", "l_partkey", "l_extendedprice")
    day = F.floor(micros("l_shipdate") / F.lit(86400000000)).cast("long")
    placed = rows.select(F.col("l_orderkey").alias("trip_id"), day.alias("day"), place.alias("m"))
    if not each:
        placed = placed.groupBy("trip_id", "day").agg(F.min("m").alias("m"))
    daily = placed.select("trip_id", "day", "m", (F.col("m.l_suppkey") % n).cast("int").alias("v"))
    by = Window.partitionBy("trip_id").orderBy("day", "m")
    changed = daily.withColumn("was", F.lag("v").over(by)).where("was IS NULL OR was <> v")
    return changed.select("trip_id", F.row_number().over(by).alias("stop"), "v", "day")


def token_paths(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """seq_id, path array<string>: words of documents, roles and first words of conversations, url parts of pages."""
    if table == "documents":
        return load(spark, sf_dir, table, "doc_id", "text").select(F.col("doc_id").alias("seq_id"), F.split(F.lower("text"), r"\s+").alias("path"))
    if table == "pages":
        return load(spark, sf_dir, table, "page_id", "url").select(F.col("page_id").alias("seq_id"), F.expr(r"filter(split(url, '[/:]+'), x -> x <> '')").alias("path"))
    turns = load(spark, sf_dir, table, "conv_id", "turn", "role", "text")
    symbol = F.concat_ws(":", "role", F.lower(F.split(F.coalesce("text", F.lit("")), r"\s+")[0]))
    return turns.groupBy(F.col("conv_id").alias("seq_id")).agg(F.sort_array(F.collect_list(F.struct("turn", symbol.alias("s")))).alias("p")).select("seq_id", F.col("p.s").alias("path"))


def gps_samples(spark: SparkSession, sf_dir: str, kind: str = "nation", every: int = 1) -> DataFrame:
    """trip_id, seq, x, y, t, e: noisy location fixes (e: the edge driven, for accuracy), every k-th one."""
    walk = events_walk(spark, sf_dir, kind).where("e IS NOT NULL").join(build_network(spark, sf_dir, kind), "e")
    part = F.floor(F.col("w") * (F.col("event_id") % 4 + 1) / 4)
    x = F.col("x0") + F.floor((F.col("x1") - F.col("x0")) * part / F.col("w")) + (F.col("event_id") * 7919) % 401 - 200
    y = F.col("y0") + F.floor((F.col("y1") - F.col("y0")) * part / F.col("w")) + (F.col("event_id") * 104729) % 401 - 200
    return walk.where(F.col("seq") % every == 0).select("trip_id", "seq", x.cast("long").alias("x"), y.cast("long").alias("y"), "t", "e")
