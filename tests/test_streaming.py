"""Streams against their batch twins."""

from pyspark.sql import functions as F

from roadtraj.operators import temporal
from roadtraj.streaming import online


def _points(spark, folder, rows):
    spark.createDataFrame(rows, "trip_id long, d long, t long").coalesce(1).write.mode("append").parquet(folder)


def test_online_codec_equals_batch(spark, tmp_path):
    folder = str(tmp_path / "in")
    rows = [(k, (i * i * (k + 3)) % 17 + i * 10, 1000 + i * 60 + k) for k in range(4) for i in range(30)]
    for lo in (0, 10, 20):  # three files, so three micro-batches
        _points(spark, folder, [r for r in rows if lo * 60 <= r[2] - 1000 - r[0] < (lo + 10) * 60])
    flush = [(k, 10**6, 10**7 + k) for k in range(99, 101)]
    _points(spark, folder, flush)
    raw = spark.readStream.schema("trip_id long, d long, t long").option("maxFilesPerTrigger", 1).parquet(folder)
    stream = online.stream_temporal(raw.withColumn("ts", F.timestamp_seconds("t")).withWatermark("ts", "1 second"), 20, 30, gap_ms=1000)
    got = online.run_to_table(stream, "online_codec", checkpoint=str(tmp_path / "state")).where("trip_id < 99").drop("late")
    d = spark.createDataFrame(rows, "trip_id long, d long, t long").groupBy("trip_id").agg(F.sort_array(F.collect_list(F.struct("t", "d"))).alias("s"))
    whole = d.select("trip_id", F.expr("transform(s, p -> struct(p.d as d, p.t as t))").alias("temporal"))
    want = temporal.temporal_compress(whole, 20, 30).select("trip_id", F.explode("temporal").alias("p")).select("trip_id", "p.d", "p.t")
    assert want.exceptAll(got).count() == 0 and got.exceptAll(want).count() == 0


def test_deduplicated_stream(spark, tmp_path):
    folder = str(tmp_path / "ev")
    spark.range(5).selectExpr("id as event_id", "timestamp_seconds(id + 9) as ts").unionAll(spark.range(5).selectExpr("id as event_id", "timestamp_seconds(id + 9) as ts")).write.parquet(folder)
    raw = spark.readStream.schema("event_id long, ts timestamp").parquet(folder)
    assert online.run_to_table(online.deduplicated(raw), "dedup").count() == 5


def _drain(stream, out, state):
    stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()


def test_restart_and_late_rows(spark, tmp_path):
    """A run that stops and starts again from its checkpoint keeps what one run keeps; late rows are dropped and told."""
    rows = [(k, (i * i * (k + 3)) % 17 + i * 10, 1000 + i * 60 + k) for k in range(3) for i in range(20)]
    late = [(1, 5, 1130), (1, 7, 1250)]  # before points that are already in
    schema = "trip_id long, d long, t long"
    for name, stops in (("once", False), ("again", True)):
        folder, out, state = (str(tmp_path / name / x) for x in ("in", "out", "state"))

        def stream(folder=folder):
            raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(folder)
            return online.stream_temporal(raw.withColumn("ts", F.timestamp_seconds("t")).withWatermark("ts", "1 hour"), 20, 30, gap_ms=1000)

        for part in (rows[:], late, [(99, 0, 10**7)], [(100, 0, 2 * 10**7)]):
            for chunk in ([r for r in part if r[2] < 1600], [r for r in part if r[2] >= 1600]):
                if chunk:
                    _points(spark, folder, chunk)
                    if stops:
                        _drain(stream(), out, state)
        if not stops:
            _drain(stream(), out, state)
    once, again = (spark.read.schema(online._OUT).parquet(str(tmp_path / n / "out")).where("trip_id < 99") for n in ("once", "again"))
    assert once.count() > 20 and once.exceptAll(again).count() == 0 and again.exceptAll(once).count() == 0
    assert {r.trip_id: r.late for r in once.where("late IS NOT NULL").collect()} == {0: 0, 1: 2, 2: 0}


def test_stream_to_files_keeps_rows_off_the_driver(spark, tmp_path):
    """An append stream ends up in files that hold every row once."""
    from roadtraj.streaming import online

    spark.range(100).repartition(3).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("id long").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    got = online.run_to_files(stream, str(tmp_path / "out"))
    assert got.inputFiles() and sorted(r.id for r in got.collect()) == list(range(100))
