"""Structured Streaming: the temporal codec with constant state, flow counts, trip splitting.

The codec keeps one state row for each trip: anchor, last point, two slope bounds
as fractions, and counts. Rows not later than the last point are dropped and
counted. A trip ends by event time: a watermark past its last point plus the gap
emits the last point, with the number of dropped rows, and clears the state.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from roadtraj.operators.temporal import narrow

_STATE = "started boolean, ad long, at long, pd long, pt long, ln long, lm long, hn long, hm long, late long"
_OUT = "trip_id long, d long, t long, late long"  # late: rows dropped, told with the last point


def event_stream(spark: SparkSession, sf_dir: str, per_trigger: int = 1) -> DataFrame:
    """The events table as a stream, event time in ``ts`` (UTC)."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    raw = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").option("maxFilesPerTrigger", per_trigger).parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def stream_temporal(points: DataFrame, tau: int, eta: int, gap_ms: int = 3_600_000) -> DataFrame:
    """trip_id, d, t of kept points, and ``late`` (null but with a trip's last point), in append mode. ``points``: trip_id, d, t and a watermarked ``ts``."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            s = state.get
            state.remove()
            yield pd.DataFrame([(key[0], s[3], s[4], s[9])], columns=["trip_id", "d", "t", "late"])
            return
        s = state.get if state.exists else None
        out, newest = [], 0
        for frame in frames:
            frame = frame.sort_values(["t", "d"])
            newest = max(newest, int(frame["ts"].max().timestamp() * 1000))
            for d, t in zip(frame["d"].tolist(), frame["t"].tolist(), strict=True):
                if s is None:
                    out.append((key[0], d, t, None))
                    s = (True, d, t, d, t, 0, 1, 1, 0, 0)
                    continue
                _, ad, at, pd_, pt, ln, lm, hn, hm, late = s
                if t <= pt:
                    s = (*s[:9], late + 1)
                    continue
                dd, dt, lo, hi = d - ad, t - at, (ln, lm), (hn, hm)
                if dd * lo[1] >= lo[0] * dt and dd * hi[1] <= hi[0] * dt:
                    lo, hi = narrow(lo, hi, dd, dt, tau, eta)
                else:
                    if (pd_, pt) != (ad, at):
                        out.append((key[0], pd_, pt, None))
                    ad, at = pd_, pt
                    lo, hi = narrow((0, 1), (1, 0), d - ad, t - at, tau, eta)
                s = (True, ad, at, d, t, *lo, *hi, late)
        if s is not None:
            state.update(s)
            state.setTimeoutTimestamp(max(newest, state.getCurrentWatermarkMs() + 1) + gap_ms)
        yield pd.DataFrame(out, columns=["trip_id", "d", "t", "late"]).astype({"late": "Int64"})

    return points.groupBy("trip_id").applyInPandasWithState(step, _OUT, _STATE, "append", GroupStateTimeout.EventTimeTimeout)


def replay(points: DataFrame, folder: str, parts: int = 4, end_ms: int = 30 * 86_400_000) -> DataFrame:
    """A stream of points (trip_id, d, t in units of ``t_us`` microseconds as column ts) written in ``parts`` files by time, and two rows far behind the end that let open trips close."""
    spark = points.sparkSession
    cuts = [r for r in points.approxQuantile("t", [k / parts for k in range(1, parts)], 0.01)] if parts > 1 else []
    edges = [None, *cuts, None]
    for lo, hi in zip(edges, edges[1:], strict=False):
        part = points if lo is None else points.where(F.col("t") > lo)
        (part if hi is None else part.where(F.col("t") <= hi)).coalesce(1).write.mode("append").parquet(folder)
    last = points.agg(F.max("ts").alias("ts"), F.max("t").alias("t"))
    for k in (1, 2):
        flush = last.select(F.lit(-k).cast("long").alias("trip_id"), F.lit(0).cast("long").alias("d"), (F.col("t") + k).cast("long").alias("t"), (F.col("ts") + F.expr(f"make_dt_interval(0, 0, 0, {k * end_ms / 1000})")).alias("ts"))
        flush.select(*points.columns).coalesce(1).write.mode("append").parquet(folder)
    return spark.readStream.schema(points.schema).option("maxFilesPerTrigger", 1).parquet(folder)


def flow_per_hour(events: DataFrame, late: str = "10 minutes") -> DataFrame:
    """Events and users of each hour; rows later than ``late`` behind the watermark are dropped."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", "1 hour")).agg(F.count(F.lit(1)).alias("n"), F.approx_count_distinct("user_id").alias("users"))


def moving_density(events: DataFrame) -> DataFrame:
    """Events of each six hours, every hour."""
    return events.withWatermark("ts", "10 minutes").groupBy(F.window("ts", "6 hours", "1 hour")).agg(F.count(F.lit(1)).alias("n"))


def trip_sessions(events: DataFrame, gap: str = "12 hours") -> DataFrame:
    """A user's events split into trips wherever nothing happens for ``gap``."""
    return events.withWatermark("ts", "10 minutes").groupBy("user_id", F.session_window("ts", gap)).agg(F.count(F.lit(1)).alias("n"))


def deduplicated(events: DataFrame) -> DataFrame:
    """Each event_id once, with state bounded by the watermark."""
    return events.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"])


def run_to_table(stream: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Drive a stream over all available input into a memory table, and return it."""
    writer = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    query = (writer.option("checkpointLocation", checkpoint) if checkpoint else writer).start()
    query.awaitTermination()
    return stream.sparkSession.table(name)


def run_to_files(stream: DataFrame, folder: str) -> DataFrame:
    """Drive an append-mode stream over all available input into Parquet files below ``folder``, and return a scan of them: no row passes the driver."""
    out, schema = f"{folder}/rows", stream.schema
    query = stream.writeStream.format("parquet").outputMode("append").trigger(availableNow=True).option("checkpointLocation", f"{folder}/checkpoint").start(out)
    query.awaitTermination()
    return stream.sparkSession.read.schema(schema).parquet(out)
