"""Competitors: street runs, a lossy map-matched record, byte codecs.

Two of them are known by their properties only, so they are stand-ins built to
have these properties. Both bound the plane distance at equal sample times.

* ``street_runs`` keeps the path as stretches along one street and direction,
  which give the edges back, and of the sequence only what constant speed between
  kept points needs to stay within the bound: times where the street changes,
  whose distances the runs know, and samples where those do not do.
* ``lossy_matched`` keeps some of the matched samples only. Between two of them
  the recorded shortest path at constant speed stands for whatever was driven, so
  path and times are lost in part and cannot be had back. From each kept sample the
  record reaches as far ahead as the bound allows, trying every sample.

The stronger byte codecs stand in for one that is not at hand.
"""

from __future__ import annotations

import bz2
import lzma
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from roadtraj.functions.interpolate import tim_sql
from roadtraj.operators.flat import flatten, lists, map_column, offsets_of, ragged
from roadtraj.operators.measures import StorageModel
from roadtraj.operators.spatial import PairTable
from roadtraj.plans.scratch import cut
from roadtraj.operators.temporal import POINTS, opening_window
from roadtraj.sources.trips import as_temporal

CODECS = {"zip": (lambda b: zlib.compress(b, 6), zlib.decompress), "lzma": (lzma.compress, lzma.decompress), "bz2": (bz2.compress, bz2.decompress)}


def street_runs(steps: DataFrame, edges: DataFrame) -> DataFrame:
    """trip_id, run, street, first_e, first_pos, n: maximal stretches along one street in one direction."""
    by = Window.partitionBy("trip_id").orderBy("pos")
    on = steps.join(edges.select("e", "street", "tail", "head"), "e")
    turned = (F.col("street") != F.lag("street").over(by)) | (F.col("head") == F.lag("tail").over(by))
    new = on.withColumn("new", F.coalesce(turned.cast("int"), F.lit(1)))
    runs = new.withColumn("run", F.sum("new").over(by))
    return runs.groupBy("trip_id", "run", "street").agg(F.min_by("e", "pos").alias("first_e"), F.min("pos").alias("first_pos"), F.count(F.lit(1)).alias("n"))


def street_next(edges: DataFrame) -> DataFrame:
    """e, next_e: the edge that follows along the same street, without turning back."""
    own = edges.select("e", "street", "tail", "head")
    after = edges.select(F.col("e").alias("next_e"), "street", F.col("tail").alias("head"), F.col("head").alias("_to"))
    return own.join(after, ["street", "head"]).where("_to <> tail").groupBy("e").agg(F.min("next_e").alias("next_e"))


def street_expand(runs: DataFrame, edges: DataFrame) -> DataFrame:
    """trip_id, pos, e: the steps again. Places along a street double in each round, as in ``expand_pairs``, and are cut from the rounds before."""
    jump = cut(street_next(edges))
    kinds = runs.groupBy("first_e").agg(F.max("n").alias("most"))
    places = cut(kinds.select("first_e", F.lit(0).alias("i"), F.col("first_e").alias("e"), "most"))
    width, most = 1, runs.agg(F.max("n")).first()[0] or 0
    while width < most:
        ahead = cut(places.where(F.col("i") + width < F.col("most")).join(jump, "e").select("first_e", (F.col("i") + width).alias("i"), F.col("next_e").alias("e"), "most"))
        places = places.unionByName(ahead)
        jump = cut(jump.join(jump.select(F.col("e").alias("next_e"), F.col("next_e").alias("_far")), "next_e").select("e", F.col("_far").alias("next_e")))
        width *= 2
    return runs.join(places.drop("most"), "first_e").where("i < n").select("trip_id", (F.col("first_pos") + F.col("i")).cast("int").alias("pos"), "e")


def street_sequence(runs: DataFrame, points: DataFrame, edges: DataFrame, steps: DataFrame, eps: int) -> DataFrame:
    """trip_id, temporal, changes: kept points, the samples staying within ``eps`` at their times; how many of them are street changes."""
    by = Window.partitionBy("trip_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
    cum = steps.join(edges.select("e", "w"), "e").withColumn("d", F.sum("w").over(by))
    ends = cum.join(runs.select("trip_id", (F.col("first_pos") + F.col("n") - 1).alias("pos")), ["trip_id", "pos"]).select("trip_id", "d")
    temporal = as_temporal(points)
    within = ends.join(temporal, "trip_id").where("d > temporal[0].d AND d < element_at(temporal, -1).d")
    at = within.select("trip_id", "d", F.expr(tim_sql("temporal", "d")).cast("long").alias("t"))
    both = at.withColumn("turn", F.lit(1)).unionByName(points.select("trip_id", "d", "t", F.lit(0).alias("turn"))).groupBy("trip_id", "t").agg(F.max("d").alias("d"), F.max("turn").alias("turn"))
    kept = opening_window(as_temporal(both), eps, None)
    turns = both.where("turn = 1").groupBy("trip_id").agg(F.collect_list("t").alias("_turns"))
    counted = F.expr("size(filter(temporal, p -> array_contains(_turns, p.t)))")
    return kept.join(turns, "trip_id", "left").select("trip_id", "temporal", F.when(F.col("_turns").isNull(), 0).otherwise(counted).cast("long").alias("changes"))


def street_run_bits(runs: DataFrame, sequence: DataFrame, model: StorageModel) -> DataFrame:
    """trip_id, bits: runs as (first edge, length); a change point is a time, another point a distance and a time."""
    n = runs.groupBy("trip_id").agg(F.count(F.lit(1)).alias("runs"))
    size = F.col("runs") * (model.edge_bits + 16) + F.col("changes") * (model.tuple_bits // 2) + (F.size("temporal") - F.col("changes")) * model.tuple_bits
    return n.join(sequence, "trip_id").select("trip_id", size.cast("long").alias("bits"))


class Ground(PairTable):
    """A pair table with the coordinates of edges."""

    @staticmethod
    def collect(sp: DataFrame, edges: DataFrame) -> Ground:
        out = Ground.__new__(Ground)
        out.__dict__.update(PairTable.collect(sp, edges).__dict__)  # checks the sizes
        ends = edges.select("e", "x0", "y0", "x1", "y1").toArrow()
        out.line = np.zeros((len(out.tail), 4), np.int64)
        out.line[ends.column("e").to_numpy()] = np.stack([ends.column(c).to_numpy() for c in ("x0", "y0", "x1", "y1")], axis=1)
        return out

    def places(self, path: np.ndarray, d: np.ndarray) -> np.ndarray:
        """Plane positions at distances from the start of a path, rounded down."""
        ends = np.cumsum(self.w[path])
        at = np.minimum(np.searchsorted(ends, d, side="right"), len(path) - 1)
        line, w = self.line[path[at]], self.w[path[at]]
        part = d - (ends[at] - w)
        return line[:, :2] + (line[:, 2:] - line[:, :2]) * part[:, None] // w[:, None]

    def on_bridges(self, u: np.ndarray, v: np.ndarray, which: np.ndarray, rel: np.ndarray) -> np.ndarray:
        """The edge, and the distance of its start, at ``rel`` along the recorded path u[which] to v[which]; -1 behind the path's end."""
        edge, bounds = self.walk(u, v)
        total = np.cumsum(self.w[edge])
        start = np.concatenate([[0], total])[bounds[:-1]]
        at = np.searchsorted(total, start[which] + rel, side="right")
        inside = at < bounds[1:][which]
        found = edge[np.minimum(at, max(len(edge) - 1, 0))] if len(edge) else np.full(len(at), -1, np.int32)
        begin = total[np.minimum(at, max(len(edge) - 1, 0))] - self.w[found] - start[which] if len(edge) else np.zeros(len(at), np.int64)
        return np.where(inside, found, -1), begin


_MOST_TESTED = 1 << 20  # samples that are held against bridges at once


def _on_path(ground: Ground, path: np.ndarray, offsets: np.ndarray, d: np.ndarray, trip: np.ndarray, side: str) -> tuple[np.ndarray, np.ndarray]:
    """Places in the flat paths that distances fall on, and the distance of each edge's start on its trip."""
    total = np.cumsum(ground.w[path])
    base = np.concatenate([[0], total])[offsets[:-1]]
    begin = total - ground.w[path] - np.repeat(base, np.diff(offsets))
    # Distances behind a trip's end stay on its last edge, those before its start on its first.
    at = np.searchsorted(total, base[trip] + d, side=side)
    return np.clip(at, offsets[:-1][trip], offsets[1:][trip] - 1), begin


def _lossy_trips(path: np.ndarray, paths_at: np.ndarray, d: np.ndarray, t: np.ndarray, samples_at: np.ndarray, ground: Ground, eps: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of flat trips: kept paths and their offsets, kept samples and their offsets, distances of kept samples on the kept paths.

    All trips take their next kept sample in common; every later sample is tried,
    and the farthest whose bridge stays within ``eps`` of all samples passed is taken.
    """
    n = len(samples_at) - 1
    trip = np.repeat(np.arange(n), np.diff(samples_at))
    right, begin = _on_path(ground, path, paths_at, d, trip, "right")
    line = ground.line[path[right]]
    here = line[:, :2] + (line[:, 2:] - line[:, :2]) * (d - begin[right])[:, None] // ground.w[path[right]][:, None]
    at, _ = _on_path(ground, path, paths_at, d, trip, "left")  # a sample at an edge's end is on that edge
    e, off = path[at], d - begin[at]

    def fits(i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Whether the recorded path from sample i to sample j passes all samples between within the bound."""
        u, v = ground.head[e[i]], ground.tail[e[j]]
        same = (e[i] == e[j]) & (off[j] >= off[i])
        hop = ground.find(u, v)
        good = same | (u == v) | (hop >= 0)
        direct = (u == v) | (hop < 0) | same
        first = ground.w[e[i]] + np.where(direct, 0, ground.dist[np.where(direct, 0, hop)] if len(ground.dist) else 0)  # where edge e[j] starts
        first = np.where(same, 0, first)
        upto = first + off[j]
        passed = j - i - 1
        row, k = np.repeat(np.arange(len(i)), passed), ragged(i + 1, passed)
        a, b = i[row], j[row]
        with np.errstate(divide="ignore"):  # samples of one time all stand at the first one's place
            moved = off[a] + (upto - off[i])[row] * (t[k] - t[a]) // (t[b] - t[a])
        edge, start = np.where(moved < ground.w[e[a]], e[a], e[b]), np.where(moved < ground.w[e[a]], 0, first[row])
        edge, start = np.where(same[row], e[a], edge), np.where(same[row], 0, start)
        between = np.flatnonzero(~direct[row] & (moved >= ground.w[e[a]]) & (moved < first[row]))
        if len(between):
            code, which = np.unique(u[row[between]].astype(np.int64) * ground.vertices + v[row[between]], return_inverse=True)
            found, begins = ground.on_bridges(code // ground.vertices, code % ground.vertices, which, moved[between] - ground.w[e[a[between]]])
            edge[between], start[between] = found, begins + ground.w[e[a[between]]]
        line, w = ground.line[edge], ground.w[edge]
        gap = line[:, :2] + (line[:, 2:] - line[:, :2]) * (moved - start)[:, None] // w[:, None] - here[k]
        bad = (gap * gap).sum(1) > eps * eps
        return good & (np.bincount(row[bad], minlength=len(i)) == 0)

    last = samples_at[1:] - 1
    now = samples_at[:-1].copy()
    moves = []
    while True:
        open_ = np.flatnonzero(now < last)
        if not len(open_):
            break
        i = now[open_]
        best = i + 1  # the next sample is always in reach: along the trip's own edges
        # Candidates from the farthest on, a share of each trip's samples at a time, until one fits.
        upto, left = last[open_].copy(), np.arange(len(open_))
        while len(left):
            left = left[upto[left] > i[left] + 1]
            if not len(left):
                break
            # As many of the farthest ones as the bound on samples allows, one at least.
            width = max(1, int(_MOST_TESTED // max(1, int((upto[left] - i[left]).sum()))))
            count = np.minimum(upto[left] - i[left] - 1, min(width, 8))
            row, j = np.repeat(left, count), ragged(upto[left] - count + 1, count)
            good = fits(i[row], j)
            np.maximum.at(best, row[good], j[good])
            upto[left] -= count
            left = left[best[left] == i[left] + 1]
        moves.append((open_, i, best))
        now[open_] = best
    who, a, b = (np.concatenate([m[c] for m in moves]) if moves else np.zeros(0, np.int64) for c in range(3))
    order = np.argsort(who, kind="stable")
    who, a, b = who[order], a[order], b[order]

    own, same = b == a + 1, (e[a] == e[b]) & (off[b] >= off[a])
    bridged = np.flatnonzero(~own & ~same)
    walked, bounds = ground.walk(ground.head[e[a[bridged]]], ground.tail[e[b[bridged]]])
    size = np.where(own, at[b] - at[a], 0)
    size[bridged] = np.diff(bounds) + 1
    far = np.where(own, begin[at[b]] - begin[at[a]], 0)  # from the start of one sample's edge to the other's
    hops = np.concatenate([[0], np.cumsum(ground.w[walked])])
    far[bridged] = ground.w[e[a[bridged]]] + hops[bounds[1:]] - hops[bounds[:-1]]

    # Each trip is its first edge and then what each move adds.
    more = np.bincount(who, minlength=n)
    kept_at, entry = offsets_of(1 + more), np.zeros(n + len(who), np.int64)
    slot = np.arange(len(who)) + who + 1
    kept = np.empty(n + len(who), np.int64)
    kept[kept_at[:-1]], kept[slot] = samples_at[:-1], b
    entry[slot] = far
    edge_start = np.cumsum(entry)
    reach = edge_start - np.repeat(edge_start[kept_at[:-1]], np.diff(kept_at)) + off[kept]
    length = np.ones(n + len(who), np.int64)
    length[slot] = size
    place = offsets_of(length)
    out = np.empty(int(place[-1]), np.int32)
    out[place[kept_at[:-1]]] = e[samples_at[:-1]]
    mine = np.flatnonzero(own)
    out[ragged(place[slot[mine]], size[mine])] = path[ragged(at[a[mine]] + 1, size[mine])]
    out[ragged(place[slot[bridged]], np.diff(bounds))] = walked
    out[place[slot[bridged]] + np.diff(bounds)] = e[b[bridged]]
    return out, place[kept_at], kept, kept_at, reach


def _lossy(path: np.ndarray, d: np.ndarray, t: np.ndarray, ground: Ground, eps: int) -> tuple[list[int], np.ndarray, np.ndarray]:
    """Kept samples of one trip, the path that stands for it, and distances of the kept samples on it."""
    line, _, kept, _, reach = _lossy_trips(path, np.array([0, len(path)]), d, t, np.array([0, len(d)]), ground, eps)
    return kept.tolist(), line, reach


_LOSSY = pa.schema([("trip_id", pa.int64()), ("path", pa.list_(pa.int32())), ("temporal", pa.list_(pa.struct([("d", pa.int64()), ("t", pa.int64())])))])


def lossy_matched(trips: DataFrame, sp: DataFrame, edges: DataFrame, eps: int) -> DataFrame:
    """trip_id, path, temporal of rows with these columns: the samples kept, and the path that recorded shortest paths make of them."""
    shared = trips.sparkSession.sparkContext.broadcast(Ground.collect(sp, edges))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ground = shared.value
        for batch in batches:
            path, paths_at = flatten(batch.column("path"))
            column = batch.column("temporal")
            points, samples_at = column.flatten(), offsets_of(column.value_lengths().to_numpy())
            d, t = (points.field(c).to_numpy() for c in "dt")
            line, line_at, kept, kept_at, reach = _lossy_trips(path, paths_at, d, t, samples_at, ground, eps)
            sequence = pa.StructArray.from_arrays([pa.array(reach), pa.array(t[kept])], names=["d", "t"])
            yield pa.RecordBatch.from_arrays([batch.column("trip_id"), lists(line, line_at, pa.int32(), column), lists(sequence, kept_at, sequence.type, column)], schema=_LOSSY)

    usable = trips.where((F.size("path") > 0) & (F.size("temporal") > 0)).select("trip_id", "path", "temporal")
    return usable.mapInArrow(run, f"trip_id long, path array<int>, temporal {POINTS}")


def lossy_matched_bits(kept: DataFrame, model: StorageModel) -> DataFrame:
    """trip_id, bits: an edge, a distance on it and a time for each sample that is kept."""
    return kept.select("trip_id", (F.size("temporal") * (model.edge_bits + model.tuple_bits)).cast("long").alias("bits"))


def serialise(column: pa.Array) -> list[bytes]:
    """x, y, t of each list of samples as doubles, in order."""
    offsets = offsets_of(column.value_lengths().fill_null(0).to_numpy()).tolist()
    flat = column.flatten()
    body = np.stack([flat.field(c).cast(pa.float64()).to_numpy() for c in ("x", "y", "t")], axis=1).astype("<f8").tobytes()
    return [body[24 * a : 24 * b] for a, b in zip(offsets, offsets[1:], strict=False)]


def byte_compress(samples: DataFrame, codec: str) -> DataFrame:
    """``samples`` (array of x, y, t) becomes the codec's bytes."""
    press = CODECS[codec][0]
    return map_column(samples, "samples", samples.sparkSession.sparkContext.broadcast(None), lambda column, _: pa.array([press(b) for b in serialise(column)], pa.binary()), "binary")


def byte_decompress(packed: DataFrame, codec: str) -> DataFrame:
    """The samples again, as doubles."""
    unpress = CODECS[codec][1]

    def unpack(column: pa.Array, _) -> pa.Array:
        bodies = [unpress(b) for b in column.to_pylist()]
        flat = np.frombuffer(b"".join(bodies), "<f8").reshape(-1, 3)
        values = pa.StructArray.from_arrays([pa.array(np.ascontiguousarray(flat[:, k])) for k in range(3)], names=["x", "y", "t"])
        return lists(values, offsets_of([len(b) // 24 for b in bodies]), values.type, column)

    return map_column(packed, "samples", packed.sparkSession.sparkContext.broadcast(None), unpack, "array<struct<x: double, y: double, t: double>>")


def codec_bits(samples: DataFrame, codec: str) -> DataFrame:
    """trip_id, raw_bits, bits: a trip's serialised samples and their size under a byte codec."""
    packed = byte_compress(samples.select("trip_id", (F.size("samples") * 192).cast("long").alias("raw_bits"), "samples"), codec)
    return packed.select("trip_id", "raw_bits", (F.octet_length("samples") * 8).cast("long").alias("bits"))
