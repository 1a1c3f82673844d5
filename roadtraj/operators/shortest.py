"""All-pairs shortest paths over vertex pairs, with one canonical path for each pair.

Of the edges that end a shortest path to v, the one of smallest id is recorded;
so every part of a recorded path is recorded itself.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from roadtraj.operators.flat import offsets_of, ragged
from roadtraj.plans.guards import bounded
from roadtraj.plans.scratch import cut

MOST_BYTES = 640 << 20  # of the adjacency that a search holds
_EDGE_BYTES = 28
_FAR = np.iinfo(np.int64).max // 2
_CELLS = 1 << 19  # distances that a task holds at a time
_TASK_PAIRS = 1 << 18
_ROWS = 1 << 17  # of a batch that leaves a task


def _min_plus(edges: DataFrame, radius: int | None) -> DataFrame:
    """Doubling: paths of up to 2^k edges from pairs of up to 2^(k-1), until nothing shortens."""
    near = edges.groupBy(F.col("tail").alias("u"), F.col("head").alias("v")).agg(F.min("w").alias("dist"))
    stay = edges.select(F.col("tail").alias("u")).union(edges.select("head")).distinct().select("u", F.col("u").alias("v"), F.lit(0).cast("long").alias("dist"))
    best = cut(near.where("u <> v").unionByName(stay))
    while True:
        onward = best.select(F.col("u").alias("v"), F.col("v").alias("to"), F.col("dist").alias("more"))
        longer = best.join(onward, "v").select("u", F.col("to").alias("v"), (F.col("dist") + F.col("more")).alias("dist"))
        if radius is not None:
            longer = longer.where(F.col("dist") <= radius)
        after = cut(longer.groupBy("u", "v").agg(F.min("dist").alias("dist")))
        was, now = best.agg(F.count(F.lit(1)), F.sum("dist")).first(), after.agg(F.count(F.lit(1)), F.sum("dist")).first()
        best = after
        if tuple(was) == tuple(now):
            return best


class Searches:
    """Shortest paths from many sources at once, over a network that fits into a task."""

    def __init__(self, e: np.ndarray, tail: np.ndarray, head: np.ndarray, w: np.ndarray):
        self.vertices = int(max(tail.max(initial=-1), head.max(initial=-1))) + 1
        out, into = np.argsort(tail, kind="stable"), np.lexsort((e, head))
        # Edges out of vertex u stand from out[u] to out[u + 1], those into it from into[u] on, by id.
        self.out, self.to, self.out_w = offsets_of(np.bincount(tail, minlength=self.vertices)), head[out], w[out]
        self.into, self.came, self.in_w, self.in_e = offsets_of(np.bincount(head, minlength=self.vertices)), tail[into], w[into], e[into]
        self.most_in = int(np.diff(self.into).max(initial=0))
        self.band = max(int(w.min(initial=1)), int(w.mean()) // 4, 1) if len(w) else 1

    @staticmethod
    def collect(edges: DataFrame) -> Searches:
        rows = bounded(edges.select("e", "tail", "head", "w"), MOST_BYTES // _EDGE_BYTES, "the edge table").toArrow()
        return Searches(*(rows.column(c).to_numpy() for c in ("e", "tail", "head", "w")))

    def reach(self, sources: np.ndarray, dist: np.ndarray, radius: int | None) -> np.ndarray:
        """Places reached, ascending: number of the source times vertices, plus vertex. ``dist`` gets their distances.

        All sources go on in common, one band of distances after the other; within a
        band places lead on until none comes nearer.
        """
        start = np.arange(len(sources)) * self.vertices + sources
        dist[start] = 0
        found, waiting = [start], start
        while len(waiting):
            near = dist[waiting]
            limit = near.min() + self.band
            front, waiting = np.unique(waiting[near < limit]), waiting[near >= limit]
            while len(front):
                at = front % self.vertices
                count = self.out[at + 1] - self.out[at]
                edge = ragged(self.out[at], count)
                place, d = np.repeat(front - at, count) + self.to[edge], np.repeat(dist[front], count) + self.out_w[edge]
                nearer = d < dist[place] if radius is None else (d < dist[place]) & (d <= radius)
                place, d = place[nearer], d[nearer]
                np.minimum.at(dist, place, d)
                place = np.unique(place)
                found.append(place)
                now = dist[place] < limit
                front, waiting = place[now], np.concatenate([waiting, place[~now]])
        return np.unique(np.concatenate(found))

    def last(self, sources: np.ndarray, places: np.ndarray, dist: np.ndarray) -> np.ndarray:
        """Which of the edges into each place is the smallest that ends a shortest path, -1 at the source itself."""
        at, which = places % self.vertices, np.full(len(places), -1)
        left, k = np.flatnonzero(at != sources[places // self.vertices]), 0
        while len(left):
            edge = self.into[at[left]] + k
            tight = dist[places[left] - at[left] + self.came[edge]] + self.in_w[edge] == dist[places[left]]
            which[left[tight]] = k
            left, k = left[~tight], k + 1
        return which

    def blocks(self, sources: np.ndarray, radius: int | None = None) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """Sources, places reached from them, distances and last edges (as ``last`` numbers them), some sources at a time."""
        some = max(1, min(_CELLS // max(self.vertices, 1), len(sources)))
        dist = np.full(some * self.vertices, _FAR)
        for i in range(0, len(sources), some):
            own = sources[i : i + some].astype(np.int64)
            places = self.reach(own, dist, radius)
            yield own, places, dist[places], self.last(own, places, dist)
            dist[places] = _FAR


def _sources(edges: DataFrame, vertices: int) -> DataFrame:
    """u, spread over tasks so that each finds about ``_TASK_PAIRS`` pairs of a network where all are within reach."""
    every = edges.select(F.col("tail").alias("u")).union(edges.select("head")).distinct()
    return every.repartition(max(1, min(vertices * vertices // _TASK_PAIRS, vertices, 4096)))


def _dijkstra(edges: DataFrame, radius: int | None) -> DataFrame:
    """u, v, dist, last_edge by searches from each vertex; the network goes to every task, once its size is checked. No pair is shuffled."""
    searches = Searches.collect(edges)
    shared = edges.sparkSession.sparkContext.broadcast(searches)

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        s = shared.value
        for batch in batches:
            for own, places, dist, which in s.blocks(batch.column("u").to_numpy(), radius):
                v = places % s.vertices
                last = s.in_e[np.where(which < 0, 0, s.into[v] + which)] if len(s.in_e) else which
                columns = [pa.array(own[places // s.vertices], pa.int32()), pa.array(v, pa.int32()), pa.array(dist, pa.int64()), pa.array(last, pa.int32(), mask=which < 0)]
                rows = pa.RecordBatch.from_arrays(columns, names=["u", "v", "dist", "last_edge"])
                yield from (rows.slice(i, _ROWS) for i in range(0, len(rows), _ROWS))

    return _sources(edges, searches.vertices).mapInArrow(search, "u int, v int, dist long, last_edge int")


def path_trees(edges: DataFrame, searches: Searches) -> DataFrame:
    """u, reached, slots: for each source the vertices within reach, and for each vertex which of the edges into it ends the recorded path.

    A slot is as wide as the largest number of edges into a vertex asks for, a byte
    on road networks; that number itself says that no edge does.
    """
    shared = edges.sparkSession.sparkContext.broadcast(searches)

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        s = shared.value
        for batch in batches:
            for own, places, _, which in s.blocks(batch.column("u").to_numpy()):
                slots = np.full((len(own), s.vertices), s.most_in, np.min_scalar_type(s.most_in))
                slots.reshape(-1)[places] = np.where(which < 0, s.most_in, which)
                reached = np.bincount(places // s.vertices, minlength=len(own))
                yield pa.RecordBatch.from_arrays([pa.array(own, pa.int32()), pa.array(reached, pa.int32()), pa.array([row.tobytes() for row in slots], pa.binary())], names=["u", "reached", "slots"])

    return _sources(edges, searches.vertices).mapInArrow(search, "u int, reached int, slots binary")


def shortest_pairs(edges: DataFrame, method: str = "minplus", radius: int | None = None) -> DataFrame:
    """u, v, dist. ``method``: minplus (joins) or dijkstra (searches from each source); ``radius`` bounds the distance."""
    return {"minplus": _min_plus, "dijkstra": _dijkstra}[method](edges, radius).select("u", "v", "dist")


def last_edges(pairs: DataFrame, edges: DataFrame) -> DataFrame:
    """u, v, dist, last_edge: the smallest edge that ends a shortest path; null where u = v."""
    tight = pairs.join(edges.select("e", F.col("tail").alias("v"), "head", "w"), "v").select("u", F.col("head").alias("v"), (F.col("dist") + F.col("w")).alias("through"), "e")
    ends = tight.join(pairs, ["u", "v"]).where("through = dist AND u <> v").groupBy("u", "v").agg(F.min("e").alias("last_edge"))
    return pairs.join(ends, ["u", "v"], "left").select("u", "v", "dist", F.col("last_edge").cast("int"))


def build_pairs(edges: DataFrame, method: str = "minplus", radius: int | None = None) -> DataFrame:
    """The shortest-path table: u, v, dist, last_edge."""
    return _dijkstra(edges, radius) if method == "dijkstra" else last_edges(shortest_pairs(edges, method, radius), edges)


def expand_pairs(wanted: DataFrame, sp: DataFrame, edges: DataFrame) -> DataFrame:
    """u, v, back, e: the edges of the recorded path of each wanted pair; back counts from its end.

    Places on a path double in each round: from every place found, one jump of
    as many edges as there are rounds' powers of two leads on. So rounds, each one
    join of the places and one of the jumps with themselves, follow the logarithm of the
    longest path, and nothing is broadcast.
    """
    tails = edges.select("e", F.col("tail").alias("to"))
    step = sp.where("last_edge IS NOT NULL").select("u", F.col("v").alias("at"), F.col("last_edge").alias("e"))
    jump = step.join(tails, "e").select("u", "at", "to").where("u <> to")  # a place before the path's start is none
    places = cut(wanted.select("u", "v").distinct().where("u <> v").select("u", "v", F.col("v").alias("at"), F.lit(0).alias("back")))
    width = 1
    while True:
        ahead = cut(places.join(jump, ["u", "at"]).select("u", "v", F.col("to").alias("at"), (F.col("back") + width).alias("back")))
        if ahead.isEmpty():
            break
        places = places.unionByName(ahead)
        onward = jump.select("u", F.col("at").alias("to"), F.col("to").alias("end"))
        jump, width = cut(jump.join(onward, ["u", "to"]).select("u", "at", F.col("end").alias("to"))), 2 * width
    return places.join(step, ["u", "at"]).select("u", "v", "back", "e")


def check_containment(sp: DataFrame, edges: DataFrame) -> DataFrame:
    """u, v of pairs whose path without its last edge is not recorded, or has another length: none if all is well."""
    tails = edges.select(F.col("e").alias("last_edge"), F.col("tail").alias("mid"), "w")
    before = sp.select("u", F.col("v").alias("mid"), F.col("dist").alias("d_mid"), F.col("last_edge").alias("mid_edge"))
    joined = sp.where("last_edge IS NOT NULL").join(tails, "last_edge").join(before, ["u", "mid"], "left")
    return joined.where("d_mid IS NULL OR d_mid + w <> dist OR (mid <> u AND mid_edge IS NULL)").select("u", "v")
