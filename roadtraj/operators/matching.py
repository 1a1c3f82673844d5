"""Map matching and gap filling: from noisy fixes to consecutive edges.

Candidates are found by an equi-join on grid cells. ``nearest`` takes the
closest edge; ``viterbi`` the sequence of least squared distances plus the
difference between driven and straight distance, all trips of a batch in step.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from roadtraj.functions.geometry import nearest_part, point_segment_squared
from roadtraj.operators.flat import alive, offsets_of, ragged, steps
from roadtraj.operators.spatial import PairTable, sp_decompress


def candidates(samples: DataFrame, edges: DataFrame, radius: int) -> DataFrame:
    """trip_id, seq, x, y, t, e, gap: all edges within ``radius`` of each fix."""
    cells = lambda lo, hi: F.sequence(F.floor(lo / radius), F.floor(hi / radius))
    tiled = edges.withColumn("cx", F.explode(cells(F.least("x0", "x1") - radius, F.greatest("x0", "x1") + radius))).withColumn("cy", F.explode(cells(F.least("y0", "y1") - radius, F.greatest("y0", "y1") + radius)))
    placed = samples.withColumns({"cx": F.floor(F.col("x") / radius), "cy": F.floor(F.col("y") / radius)})
    gap = point_segment_squared(*[F.col(c).cast("double") for c in ("x", "y", "x0", "y0", "x1", "y1")])
    near = placed.join(tiled, ["cx", "cy"]).withColumn("gap", F.floor(gap + 0.5)).where(F.col("gap") <= float(radius) * radius)
    return near.select("trip_id", "seq", "x", "y", "t", near["e"], "gap")


def match_trips(samples: DataFrame, edges: DataFrame, sp: DataFrame | None = None, radius: int = 450, mode: str = "nearest") -> DataFrame:
    """trip_id, seq, e of each fix with an edge in reach."""
    near = candidates(samples.drop("e"), edges, radius)
    if mode == "nearest":
        return near.groupBy("trip_id", "seq").agg(F.min(F.struct("gap", "e")).alias("m")).select("trip_id", "seq", "m.e")
    shared = samples.sparkSession.sparkContext.broadcast(PairTable.collect(sp, edges))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fixes = batch.column("fixes")
            fix, fix_at = fixes.flatten(), offsets_of(fixes.value_lengths().to_numpy())
            near_ = fix.field("near")
            start, stop = near_.offsets[:-1].to_numpy(), near_.offsets[1:].to_numpy()
            values = near_.values
            e, gap = (values.field(c).to_numpy() for c in ("e", "gap"))
            x, y = (fix.field(c).to_numpy().astype(np.float64) for c in "xy")
            best = _best_edges(shared.value, fix_at, start.astype(np.int64), (stop - start).astype(np.int64), e, gap, x, y)
            trip = np.repeat(batch.column("trip_id").to_numpy(), np.diff(fix_at))
            yield pa.RecordBatch.from_arrays([pa.array(trip, pa.int64()), fix.field("seq").cast(pa.int32()), pa.array(best, pa.int32())], names=["trip_id", "seq", "e"])

    layers = near.groupBy("trip_id", "seq").agg(F.first("x").alias("x"), F.first("y").alias("y"), F.sort_array(F.collect_list(F.struct("gap", "e"))).alias("near"))
    rows = layers.groupBy("trip_id").agg(F.sort_array(F.collect_list(F.struct("seq", "x", "y", "near"))).alias("fixes"))
    return rows.mapInArrow(run, "trip_id long, seq int, e int")


def _best_edges(pairs: PairTable, fix_at: np.ndarray, start: np.ndarray, count: np.ndarray, e: np.ndarray, gap: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """The edge of each fix of flat trips. ``start`` and ``count``: where a fix's candidates stand, by gap and edge.

    All trips take their next fix in common. Of equally cheap ways the one over the
    candidate that stands first is taken, as at a trip's last fix.
    """
    _, first, length = steps(fix_at)
    cost, back = np.empty(len(e)), np.zeros(len(e), np.int64)
    own = ragged(start[first], count[first])
    cost[own] = gap[own]
    for k in range(1, int(length.max(initial=0))):
        here = first[: alive(length, k)] + k
        was = here - 1
        # The square root itself, which rounds to the nearest; a power of a half may not.
        straight = np.sqrt((x[here] - x[was]) ** 2 + (y[here] - y[was]) ** 2)
        # One row for each candidate, and within it one for each candidate before.
        goes, owner = ragged(start[here], count[here]), np.repeat(np.arange(len(here)), count[here])
        ways = count[was][owner]
        came = ragged(start[was][owner], ways)
        through = cost[came] + _turns(pairs, e[came], np.repeat(e[goes], ways), np.repeat(straight[owner], ways))
        bounds = offsets_of(ways)[:-1]
        least = np.minimum.reduceat(through, bounds)
        hit = np.where(through == np.repeat(least, ways), np.arange(len(through)), len(through))
        back[goes] = came[np.minimum.reduceat(hit, bounds)]
        cost[goes] = least + gap[goes]
    final = fix_at[1:][np.diff(fix_at) > 0] - 1
    rows, ways = ragged(start[final], count[final]), count[final]
    bounds = offsets_of(ways)[:-1]
    least = np.minimum.reduceat(cost[rows], bounds) if len(rows) else cost[rows]
    hit = np.where(cost[rows] == np.repeat(least, ways), np.arange(len(rows)), len(rows))
    chosen = np.zeros(len(x), np.int64)
    chosen[final] = rows[np.minimum.reduceat(hit, bounds)] if len(rows) else rows
    for k in range(int(length.max(initial=0)) - 1, 0, -1):
        here = first[: alive(length, k)] + k
        chosen[here - 1] = back[chosen[here]]
    return e[chosen]


def _turns(pairs: PairTable, came: np.ndarray, goes: np.ndarray, straight: np.ndarray) -> np.ndarray:
    """Costs of going from edges to edges: how far the driven distance is from the straight one."""
    u, v = pairs.head[came], pairs.tail[goes]
    at = pairs.find(u, v)
    hop = np.where(u == v, 0, np.where(at >= 0, pairs.dist[at], -1))
    cost = np.where(hop < 0, 1e12, np.abs(hop.astype(np.float64) + pairs.w[goes] - straight) * 100.0)
    return np.where(came == goes, 0.0, cost)


def fill_gaps(matched: DataFrame, sp: DataFrame, edges: DataFrame) -> DataFrame:
    """trip_id, path: matched edges in order, repeats once, holes filled by shortest paths."""
    by = Window.partitionBy("trip_id").orderBy("seq")
    changed = matched.withColumn("was", F.lag("e").over(by)).where("was IS NULL OR was <> e")
    paths = changed.groupBy("trip_id").agg(F.sort_array(F.collect_list(F.struct("seq", "e"))).alias("s")).select("trip_id", F.col("s.e").alias("path"))
    return sp_decompress(paths, sp, edges)


def reformat(matched: DataFrame, samples: DataFrame, sp: DataFrame, edges: DataFrame) -> DataFrame:
    """trip_id, seq, t, d: distance of each matched fix from the start of its trip's path (see ``fill_gaps``); d never falls.

    A fix lies on its matched edge, at the nearest point of it. Runs of fixes on one
    edge share that edge's place on the path, and the place of the next run is one gap
    (the recorded path between both edges) and one edge further, so a path that
    returns to an edge, and fixes without a match, do no harm. ``trip_header`` takes the first
    distance off.
    """
    by = Window.partitionBy("trip_id").orderBy("seq")
    on = matched.select("trip_id", "seq", "e").join(edges, "e")
    changed = on.withColumns({"_e": F.lag("e").over(by), "_head": F.lag("head").over(by), "_w": F.lag("w").over(by)})
    pairs = sp.select(F.col("u").alias("_head"), F.col("v").alias("tail"), F.col("dist").alias("_hop"))
    moved = changed.join(pairs, ["_head", "tail"], "left")
    # From the start of one edge to the start of the next: the edge left behind, and the gap.
    gone = F.when(F.col("_e").isNull() | (F.col("_e") == F.col("e")), F.lit(0)).otherwise(F.col("_w") + F.when(F.col("_head") == F.col("tail"), F.lit(0)).otherwise(F.col("_hop")))
    begun = moved.withColumn("c0", F.sum(gone).over(by.rowsBetween(Window.unboundedPreceding, 0)))
    fixes = begun.join(samples.select("trip_id", "seq", "x", "y", "t"), ["trip_id", "seq"])
    part = nearest_part(*[F.col(c).cast("double") for c in ("x", "y", "x0", "y0", "x1", "y1")])
    at = fixes.withColumn("d", (F.col("c0") + F.floor(part * F.col("w"))).cast("long"))
    return at.select("trip_id", "seq", "t", F.max("d").over(by.rowsBetween(Window.unboundedPreceding, 0)).alias("d"))


def trip_header(points: DataFrame, paths: DataFrame) -> DataFrame:
    """trip_id, start_off, n_edges, n_samples, t_first, t_last, d_total: what a trip needs beside path and sequence.

    A trip may start within an edge; ``start_off`` is how far, and distances (see
    ``from_start``) count from there.
    """
    ends = points.groupBy("trip_id").agg(F.min("d").alias("start_off"), F.count(F.lit(1)).alias("n_samples"), F.min("t").alias("t_first"), F.max("t").alias("t_last"), (F.max("d") - F.min("d")).alias("d_total"))
    return ends.join(paths.select("trip_id", F.size("path").alias("n_edges")), "trip_id").select("trip_id", "start_off", "n_edges", "n_samples", "t_first", "t_last", "d_total")


def from_start(points: DataFrame, header: DataFrame) -> DataFrame:
    """The points with distances from the trip's first sample."""
    return points.join(header.select("trip_id", "start_off"), "trip_id").withColumn("d", F.col("d") - F.col("start_off")).drop("start_off")


def on_path(points: DataFrame, header: DataFrame) -> DataFrame:
    """The inverse: distances from the start of the path."""
    return points.join(header.select("trip_id", "start_off"), "trip_id").withColumn("d", F.col("d") + F.col("start_off")).drop("start_off")


def to_xyt(points: DataFrame, paths: DataFrame, edges: DataFrame) -> DataFrame:
    """trip_id, seq, x, y, t: positions of (d, t) points on their path, rounded down."""
    from roadtraj.functions.geometry import along

    by = Window.partitionBy("trip_id").orderBy("pos")
    steps = paths.select("trip_id", F.posexplode("path").alias("pos", "e")).join(edges, "e")
    cum = steps.withColumn("c1", F.sum("w").over(by.rowsBetween(Window.unboundedPreceding, 0))).withColumn("c0", F.col("c1") - F.col("w")).withColumn("final", F.max("c1").over(Window.partitionBy("trip_id")))
    hit = points.join(cum, "trip_id").where("c0 <= d AND (d < c1 OR (d = c1 AND c1 = final))").withColumn("part", F.col("d") - F.col("c0"))
    return hit.select("trip_id", "seq", along("x0", "x1", "part", "w").alias("x"), along("y0", "y1", "part", "w").alias("y"), "t")


def vertex_times(paths: DataFrame, temporal: DataFrame, edges: DataFrame) -> DataFrame:
    """trip_id, pos, t: arrival at the end of each edge, all that a vertex-time model keeps."""
    from roadtraj.functions.interpolate import tim_sql

    by = Window.partitionBy("trip_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
    steps = paths.select("trip_id", F.posexplode("path").alias("i", "e")).select("trip_id", (F.col("i") + 1).alias("pos"), "e").join(edges.select("e", "w"), "e")
    cum = steps.withColumn("d", F.sum("w").over(by))
    return cum.join(temporal, "trip_id").select("trip_id", "pos", F.expr(tim_sql("temporal", "d")).cast("long").alias("t"))
