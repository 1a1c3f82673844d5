"""Lossless spatial stage: skip edges that a recorded shortest path restores.

``sp_end(e, f)`` is the last edge before f on the recorded path from e to f: e
where f follows it, nothing where f is e itself, so a path that returns to an
edge is never skipped into one.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from roadtraj.operators.flat import alive, flatten, lists, map_column, offsets_of, ragged, steps
from roadtraj.operators.shortest import Searches, path_trees
from roadtraj.plans.guards import TooLarge, bounded

MOST_BYTES = 512 << 20  # of a pair table that tasks hold
_PAIR_BYTES, _EDGE_BYTES = 20, 16
_DENSE_BYTES = 64 << 20


class RecordedPaths:
    """What walks along recorded paths need of the edges; ``last_of`` tells the last edge of a pair's path, -1 where there is none."""

    def hold(self, edges: dict[str, np.ndarray]) -> None:
        size = int(edges["e"].max(initial=-1)) + 1
        self.tail, self.head, self.w = np.full(size, -1, np.int32), np.full(size, -1, np.int32), np.zeros(size, np.int64)
        self.tail[edges["e"]], self.head[edges["e"]], self.w[edges["e"]] = edges["tail"], edges["head"], edges["w"]

    def last_of(self, u: np.ndarray, v: np.ndarray) -> np.ndarray:
        raise NotImplementedError

    def sp_end(self, e: np.ndarray, f: np.ndarray) -> np.ndarray:
        """-1: no recorded path."""
        u, v = self.head[e], self.tail[f]
        return np.where(e == f, -1, np.where(u == v, e, self.last_of(u, v)))

    def walk(self, u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Edges of the recorded paths from each u to each v, and their offsets."""
        own, at, rows, edges, step = np.flatnonzero(u != v), v[u != v], [], [], 0
        while len(own):
            last = self.last_of(u[own], at)
            if (last < 0).any():
                raise ValueError("a pair without a recorded path")
            rows.append(own)
            edges.append(last)
            at = self.tail[last]
            more = at != u[own]
            own, at, step = own[more], at[more], step + 1
        if not rows:
            return np.zeros(0, np.int32), np.zeros(len(u) + 1, np.int64)
        row, edge, back = np.concatenate(rows), np.concatenate(edges), np.repeat(np.arange(step), [len(r) for r in rows])
        count = np.bincount(row, minlength=len(u))
        offsets = offsets_of(count)
        out = np.empty(len(edge), np.int32)
        out[offsets[row] + count[row] - 1 - back] = edge
        return out, offsets


class PairTable(RecordedPaths):
    """Last edges and distances of the pairs of a network that fits into a task; the size is checked first.

    Pairs are found by position in a sorted list, so a table bounded by radius costs
    its own size whatever the number of vertices; small networks get an index by pair on top.
    """

    def __init__(self, pairs: dict[str, np.ndarray], edges: dict[str, np.ndarray]):
        self.vertices = int(max(edges["tail"].max(initial=0), edges["head"].max(initial=0), pairs["u"].max(initial=0), pairs["v"].max(initial=0))) + 1
        code = pairs["u"].astype(np.int64) * self.vertices + pairs["v"]
        order = np.argsort(code, kind="stable")
        self.code, self.last, self.dist = code[order], pairs["last_edge"][order].astype(np.int32), pairs["dist"][order].astype(np.int64)
        self.index = None
        if self.vertices**2 * 4 <= _DENSE_BYTES:
            self.index = np.full(self.vertices**2, -1, np.int32)
            self.index[self.code] = np.arange(len(code), dtype=np.int32)
        self.hold(edges)

    @staticmethod
    def collect(sp: DataFrame, edges: DataFrame, most: int = MOST_BYTES) -> PairTable:
        got = bounded(sp.select("u", "v", "dist", F.coalesce("last_edge", F.lit(-1)).alias("last_edge")), most // _PAIR_BYTES, "the pair table").toArrow()
        ends = bounded(edges.select("e", "tail", "head", "w"), most // _EDGE_BYTES, "the edge table").toArrow()
        as_arrays = lambda t: {c: t.column(c).to_numpy() for c in t.column_names}
        return PairTable(as_arrays(got), as_arrays(ends))

    def find(self, u: np.ndarray, v: np.ndarray) -> np.ndarray:
        """Places of pairs in the table, -1 where there is none."""
        code = u.astype(np.int64) * self.vertices + v
        if self.index is not None:
            return self.index[code]
        if not len(self.code):
            return np.full(len(code), -1)
        at = np.minimum(np.searchsorted(self.code, code), len(self.code) - 1)
        return np.where(self.code[at] == code, at, -1)

    def last_of(self, u: np.ndarray, v: np.ndarray) -> np.ndarray:
        at = self.find(u, v)
        return np.where(at >= 0, self.last[at], -1) if len(self.last) else np.full(len(at), -1)


class TreeTable(RecordedPaths):
    """Recorded paths of all pairs of a network in a byte each, by a tree for each source: which of the edges into a vertex its path ends with.

    The trees come from searches in tasks, so no pair is ever a row.
    """

    def __init__(self, trees: pa.Table, searches: Searches, edges: dict[str, np.ndarray]):
        self.hold(edges)
        self.into, self.in_e, self.none = searches.into, searches.in_e, searches.most_in
        self.row = np.full(searches.vertices, -1)
        self.row[trees.column("u").to_numpy()] = np.arange(len(trees))
        self.slots = np.empty((len(trees), searches.vertices), np.min_scalar_type(self.none))
        at = 0
        for chunk in trees.column("slots").chunks:
            for tree in chunk:
                self.slots[at] = np.frombuffer(tree.as_buffer(), self.slots.dtype)
                at += 1
        self.pairs = int(trees.column("reached").to_numpy().sum())

    @staticmethod
    def collect(edges: DataFrame, most: int = MOST_BYTES) -> TreeTable:
        searches = Searches.collect(edges)
        size = searches.vertices**2 * np.min_scalar_type(searches.most_in).itemsize
        if size > most:
            raise TooLarge(f"the trees of {searches.vertices} vertices have {size} bytes, more than {most}")
        ends = edges.select("e", "tail", "head", "w").toArrow()
        return TreeTable(path_trees(edges, searches).toArrow(), searches, {c: ends.column(c).to_numpy() for c in ends.column_names})

    def last_of(self, u: np.ndarray, v: np.ndarray) -> np.ndarray:
        row = self.row[u]
        which = self.slots[row, v]
        known = (row >= 0) & (which != self.none)
        return np.where(known, self.in_e[np.where(known, self.into[v] + which, 0)], -1) if len(self.in_e) else np.full(len(row), -1)


def skip(column: pa.Array, pairs: RecordedPaths) -> pa.Array:
    """Keep an edge only where the recorded path from the last kept edge leaves the trip. All trips take a step at once."""
    path, offsets = flatten(column)
    keep = np.ones(len(path), bool)
    _, first, length = steps(offsets, 3)
    anchor = path[first]
    for i in range(1, int(length.max(initial=0)) - 1):
        n = alive(length, i + 1)
        here = path[first[:n] + i]
        kept = pairs.sp_end(anchor[:n], path[first[:n] + i + 1]) != here
        keep[first[:n] + i] = kept
        anchor[:n] = np.where(kept, here, anchor[:n])
    return lists(path[keep], offsets_of(keep)[offsets], pa.int32(), column)


def fewest(column: pa.Array, pairs: RecordedPaths) -> pa.Array:
    """Edges of the best skipping of all: how far a run from each place may go, then the cheapest chain of runs."""
    path, offsets = flatten(column)
    stop = np.repeat(offsets[1:], np.diff(offsets))
    reach = np.arange(len(path))
    own = np.flatnonzero(reach + 1 < stop)
    reach[own] += 1
    ahead = 2
    while len(own):
        own = own[own + ahead < stop[own]]
        own = own[pairs.sp_end(path[own], path[own + ahead]) == path[own + ahead - 1]]
        reach[own] += 1
        ahead += 1
    out = []
    for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True):
        cost = [1] + [b - a + 1] * (b - a - 1)
        for i, far in enumerate(reach[a:b].tolist()):
            for j in range(i + 1, far - a + 1):
                cost[j] = min(cost[j], cost[i] + 1)
        out.append(cost[-1] if b > a else 0)
    return pa.array(out, pa.int64())


def restore(column: pa.Array, pairs: RecordedPaths) -> pa.Array:
    """Skipped edges put back: recorded paths between neighbours that do not follow each other."""
    path, offsets = flatten(column)
    inner = np.ones(len(path), bool)
    inner[offsets[1:][np.diff(offsets) > 0] - 1] = False  # the last edge of a trip has no neighbour
    gap = np.flatnonzero(inner)
    gap = gap[pairs.head[path[gap]] != pairs.tail[path[gap + 1]]]
    between, bounds = pairs.walk(pairs.head[path[gap]], pairs.tail[path[gap + 1]])
    more = np.zeros(len(path), np.int64)
    more[gap] = np.diff(bounds)
    place = offsets_of(1 + more)
    out = np.empty(int(place[-1]), np.int32)
    out[place[:-1]] = path
    out[ragged(place[gap] + 1, more[gap])] = between
    return lists(out, place[offsets], pa.int32(), column)


def _with_pairs(paths: DataFrame, sp: DataFrame | RecordedPaths, edges: DataFrame, column: str, function, kind: str) -> DataFrame:
    table = sp if isinstance(sp, RecordedPaths) else PairTable.collect(sp, edges)
    return map_column(paths, column, paths.sparkSession.sparkContext.broadcast(table), function, kind)


def sp_compress(paths: DataFrame, sp: DataFrame | RecordedPaths, edges: DataFrame, column: str = "path") -> DataFrame:
    return _with_pairs(paths, sp, edges, column, skip, "array<int>")


def sp_decompress(paths: DataFrame, sp: DataFrame | RecordedPaths, edges: DataFrame, column: str = "path") -> DataFrame:
    return _with_pairs(paths, sp, edges, column, restore, "array<int>")


def sp_best_length(paths: DataFrame, sp: DataFrame | RecordedPaths, edges: DataFrame, column: str = "path") -> DataFrame:
    return _with_pairs(paths, sp, edges, column, fewest, "bigint")


def walk_pairs(wanted: DataFrame, pairs: RecordedPaths) -> DataFrame:
    """u, v, back, e as ``expand_pairs`` gives them, by walks in a table that tasks hold: one job, no rounds."""
    shared = wanted.sparkSession.sparkContext.broadcast(pairs)

    def walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            u, v = (batch.column(c).to_numpy() for c in "uv")
            path, bounds = shared.value.walk(u, v)
            count = np.diff(bounds)
            back = np.repeat(bounds[1:] - 1, count) - np.arange(len(path))
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(u, count), pa.int32()), pa.array(np.repeat(v, count), pa.int32()), pa.array(back, pa.int32()), pa.array(path, pa.int32())], names=["u", "v", "back", "e"])

    kinds = wanted.select(F.col("u").cast("int"), F.col("v").cast("int")).distinct().where("u <> v")
    return kinds.mapInArrow(walk, "u int, v int, back int, e int")


def vertex_tours(stops: DataFrame, sp: DataFrame | RecordedPaths, edges: DataFrame, column: str = "path") -> DataFrame:
    """Lists of vertices become the edges of the recorded paths from each to the next."""

    def expand(vertices: pa.Array, pairs: RecordedPaths) -> pa.Array:
        at, offsets = flatten(vertices)
        inner = np.ones(len(at), bool)
        inner[offsets[1:][np.diff(offsets) > 0] - 1] = False
        leg = np.flatnonzero(inner)
        path, bounds = pairs.walk(at[leg], at[leg + 1])
        return lists(path, bounds[offsets_of(inner)[offsets]], pa.int32(), vertices)

    return _with_pairs(stops, sp, edges, column, expand, "array<int>")


def sp_compress_lookahead(steps: DataFrame, sp: DataFrame, edges: DataFrame, reach: int = 16) -> DataFrame:
    """trip_id, pos, e of kept edges, for pair tables of any size: nothing is broadcast.

    Each edge meets those up to ``reach`` places ahead in a join with the pair
    table; how far its recorded path follows the trip is one minimum, and only
    the jumps from kept edge to kept edge are folded, one row for each trip. A
    run longer than ``reach`` is kept in parts, which costs edges but no loss.
    """
    ends = edges.select("e", "tail", "head")
    placed = steps.select("trip_id", "pos", "e").join(ends, "e")
    by = Window.partitionBy("trip_id").orderBy("pos")
    ahead = placed.withColumn("next", F.collect_list(F.struct("pos", "e", "tail")).over(by.rowsBetween(1, reach)))
    pairs = ahead.select("trip_id", "pos", F.col("e").alias("from_e"), F.col("head").alias("u"), F.posexplode("next").alias("k", "f")).select("trip_id", "pos", "from_e", "u", "k", F.col("f.e").alias("f"), F.col("f.tail").alias("v"))
    chain = pairs.withColumn("before", F.when(F.col("k") == 0, F.col("from_e")).otherwise(F.lag("f").over(Window.partitionBy("trip_id", "pos").orderBy("k"))))
    met = chain.join(sp.select("u", "v", "last_edge"), ["u", "v"], "left")
    end = F.when(F.col("from_e") == F.col("f"), None).when(F.col("u") == F.col("v"), F.col("from_e")).otherwise(F.col("last_edge"))
    # The direct successor always follows; from the second on the path must arrive over the edge before.
    broken = F.when((F.col("k") > 0) & ~F.coalesce(end == F.col("before"), F.lit(False)), F.col("k"))
    far = met.groupBy("trip_id", "pos", "from_e").agg(F.coalesce(F.min(broken), F.max("k") + 1).alias("run"))
    trips = far.groupBy("trip_id").agg(F.sort_array(F.collect_list(F.struct("pos", "run"))).alias("s"), F.max("pos").alias("final"))
    jumps = F.expr(
        "aggregate(s, named_struct('next', 1, 'kept', cast(array() as array<int>)), (a, x) -> "
        "IF(x.pos = a.next, named_struct('next', cast(x.pos + x.run as int), 'kept', concat(a.kept, array(cast(x.pos as int)))), a), a -> array_distinct(concat(a.kept, array(cast(final + 1 as int)))))"
    )
    kept = trips.select("trip_id", F.explode(jumps).alias("pos"))
    ends_only = steps.groupBy("trip_id").agg(F.max("pos").alias("pos"))
    wanted = kept.select("trip_id", F.col("pos").cast("int")).unionByName(ends_only.select("trip_id", F.col("pos").cast("int"))).distinct()
    return steps.join(wanted, ["trip_id", "pos"]).select("trip_id", "pos", "e")
