"""Queries on packed trips: whole pieces and hops are skipped by length or box, one of them is opened.

A packed trip is its sequence of pieces (grams). Between two pieces there is a
hop: the recorded path from the last edge of one to the first edge of the next.
``build_aux`` holds, once for each distinct gram and hop, its length, its box and
its edges with offsets; a trip's pieces carry running lengths. So a distance is
looked up by an interval join on pieces, and edges are joined only for the piece
or hop that holds it.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from roadtraj.functions.geometry import along, box_gap_squared
from roadtraj.functions.interpolate import dis_sql, tim_sql
from roadtraj.operators.shortest import expand_pairs
from roadtraj.operators.spatial import RecordedPaths, walk_pairs


@dataclass
class Aux:
    """spans (span, len, x0, y0, x1, y1: distinct grams and hops) and parts (span, off, e and its edge columns)."""

    spans: DataFrame
    parts: DataFrame


def trip_spans(nodes: DataFrame) -> DataFrame:
    """trip_id, k, span: grams and the hops between them, in order. A hop is 'e>f'."""
    placed = nodes.select("trip_id", F.posexplode("path").alias("i", "gram"))
    before = F.lag("gram").over(Window.partitionBy("trip_id").orderBy("i"))
    hop = F.concat(F.regexp_extract(before, "[^-]*$", 0), F.lit(">"), F.regexp_extract("gram", "^[^-]*", 0))
    both = placed.withColumn("hop", hop).select("trip_id", F.col("i"), F.explode(F.array_compact(F.array("hop", "gram"))).alias("span"))
    return both.select("trip_id", (F.col("i") * 2 - F.col("span").contains(">").cast("int")).alias("k"), "span")


def build_aux(spans: DataFrame, sp: DataFrame, edges: DataFrame, table: RecordedPaths | None = None) -> Aux:
    """Lengths, boxes and edges of every distinct span: built from shortest paths, independent of the number of trips.

    With a pair table that fits into tasks paths are walked there, else by joins.
    """
    kinds = spans.select("span").distinct()
    hop = F.col("span").contains(">")
    listed = kinds.select("span", F.posexplode(F.split("span", "[->]")).alias("i", "text")).select("span", "i", F.col("text").cast("int").alias("e"))
    ahead = Window.partitionBy("span").orderBy("i")
    links = listed.withColumn("f", F.lead("e").over(ahead)).where("f IS NOT NULL")
    ends = edges.select("e", "tail", "head")
    pairs = links.join(ends.select("e", F.col("head").alias("u")), "e").join(ends.select(F.col("e").alias("f"), F.col("tail").alias("v")), "f").where("u <> v")
    wanted = pairs.select("u", "v")
    inner = (expand_pairs(wanted, sp, edges) if table is None else walk_pairs(wanted, table)).withColumnRenamed("e", "inner_e")
    between = pairs.join(inner, ["u", "v"]).select("span", "i", (-F.col("back") - 1).alias("j"), F.col("inner_e").alias("e"))
    own = listed.where(~hop).select("span", "i", F.lit(-(1 << 30)).alias("j"), "e")
    # Edges between places i and i + 1 come after place i and before place i + 1.
    all_ = own.unionByName(between.select("span", "i", "j", "e")).join(edges, "e")
    before = Window.partitionBy("span").orderBy("i", "j").rowsBetween(Window.unboundedPreceding, -1)
    parts = all_.select("span", F.coalesce(F.sum("w").over(before), F.lit(0)).cast("long").alias("off"), "e", "w", "x0", "y0", "x1", "y1")
    box = [F.min(F.least("x0", "x1")), F.min(F.least("y0", "y1")), F.max(F.greatest("x0", "x1")), F.max(F.greatest("y0", "y1"))]
    measured = parts.groupBy("span").agg(F.sum("w").alias("len"), *[b.alias(n) for b, n in zip(box, ("x0", "y0", "x1", "y1"), strict=True)])
    spans_ = kinds.join(measured, "span", "left").select("span", F.coalesce("len", F.lit(0)).cast("long").alias("len"), "x0", "y0", "x1", "y1")
    return Aux(spans_, parts)


def placed_spans(spans: DataFrame, aux: Aux) -> DataFrame:
    """trip_id, k, span, c0, c1 (distances at its ends) and its box; empty hops are gone."""
    by = Window.partitionBy("trip_id").orderBy("k").rowsBetween(Window.unboundedPreceding, 0)
    run = spans.join(aux.spans, "span").withColumn("c1", F.sum("len").over(by)).withColumn("c0", F.col("c1") - F.col("len"))
    return run.where("len > 0").select("trip_id", "k", "span", "c0", "c1", "x0", "y0", "x1", "y1")


def raw_spans(paths: DataFrame) -> DataFrame:
    """The raw twin: every edge is a span of its own."""
    return paths.select("trip_id", F.posexplode("path").alias("i", "e")).select("trip_id", (F.col("i") * 2).alias("k"), F.col("e").cast("string").alias("span"))


def raw_aux(edges: DataFrame) -> Aux:
    parts = edges.select(F.col("e").cast("string").alias("span"), F.lit(0).cast("long").alias("off"), "e", "w", "x0", "y0", "x1", "y1")
    box = edges.select(F.col("e").cast("string").alias("span"), F.col("w").alias("len"), F.least("x0", "x1").alias("x0"), F.least("y0", "y1").alias("y0"), F.greatest("x0", "x1").alias("x1"), F.greatest("y0", "y1").alias("y1"))
    return Aux(box, parts)


def _open(hit: DataFrame, aux: Aux) -> DataFrame:
    """Spans become their edges, with distances from the trip's start: at, w and the edge's ends."""
    parts = aux.parts.select("span", "off", "e", "w", *[F.col(c).alias(f"e{c}") for c in ("x0", "y0", "x1", "y1")])
    return hit.join(parts, "span").withColumn("at", F.col("c0") + F.col("off"))


def where_at(asked: DataFrame, temporal: DataFrame, placed: DataFrame, aux: Aux) -> DataFrame:
    """qid, trip_id, x, y of q (qid, trip_id, t): rounded down. The error is at most the packed sequence's TSND."""
    d = asked.join(temporal, "trip_id").select("qid", "trip_id", F.expr(dis_sql("temporal", "t")).cast("long").alias("d"))
    last = placed.groupBy("trip_id").agg(F.max("c1").alias("total"))
    near = d.join(last, "trip_id").select("qid", "trip_id", F.least("d", F.col("total") - 1).alias("look"), F.least("d", "total").alias("d"))
    hit = near.join(placed, "trip_id").where("c0 <= look AND look < c1")
    edge = _open(hit, aux).where("at <= look AND look < at + w").withColumn("part", F.col("d") - F.col("at"))
    return edge.select("qid", "trip_id", along("ex0", "ex1", "part", "w").alias("x"), along("ey0", "ey1", "part", "w").alias("y"))


def first_passage(asked: DataFrame, placed: DataFrame, aux: Aux) -> DataFrame:
    """qid, trip_id, d of q (qid, trip_id, x, y): distance at which the trip first passes the point; points off the path give no row."""
    boxed = asked.join(placed.withColumnsRenamed({"x0": "bx0", "y0": "by0", "x1": "bx1", "y1": "by1"}), "trip_id").where("x BETWEEN bx0 AND bx1 AND y BETWEEN by0 AND by1")
    on = _open(boxed, aux).where("x BETWEEN least(ex0, ex1) AND greatest(ex0, ex1) AND y BETWEEN least(ey0, ey1) AND greatest(ey0, ey1)")
    gone = F.expr("at + (abs(x - ex0) + abs(y - ey0)) * w div (abs(ex1 - ex0) + abs(ey1 - ey0))")
    return on.groupBy("qid", "trip_id").agg(F.min(gone).alias("d"))


def when_at(asked: DataFrame, temporal: DataFrame, placed: DataFrame, aux: Aux) -> DataFrame:
    """qid, trip_id, t of q (qid, trip_id, x, y): first passage; points off the path give no row."""
    return first_passage(asked, placed, aux).join(temporal, "trip_id").select("qid", "trip_id", F.expr(tim_sql("temporal", "d")).cast("long").alias("t"))


def _clipped(df: DataFrame, lo: str = "d1", hi: str = "d2") -> DataFrame:
    """Adds the box (px0, py0, px1, py1) of the part of an edge between two distances; rows outside are gone."""
    inside = df.where(f"at <= {hi} AND {lo} <= at + w").withColumns({"a": F.greatest(F.col(lo) - F.col("at"), F.lit(0)), "b": F.least(F.col(hi) - F.col("at"), F.col("w"))})
    ends = {f"{c}{n}": along(f"e{c}0", f"e{c}1", p, "w") for c in "xy" for n, p in ((2, "a"), (3, "b"))}
    cut = inside.withColumns({f"q{k}": v for k, v in ends.items()})
    return cut.withColumns({"px0": F.least("qx2", "qx3"), "py0": F.least("qy2", "qy3"), "px1": F.greatest("qx2", "qx3"), "py1": F.greatest("qy2", "qy3")})


def _windowed(asked: DataFrame, temporal: DataFrame) -> DataFrame:
    joined = asked.join(temporal, "trip_id")
    return joined.withColumns({"d1": F.expr(dis_sql("temporal", "t1")).cast("long"), "d2": F.expr(dis_sql("temporal", "t2")).cast("long")}).drop("temporal")


def range_hit(asked: DataFrame, temporal: DataFrame, placed: DataFrame, aux: Aux) -> DataFrame:
    """qid, trip_id, hit of q (qid, trip_id, t1, t2, rx0, ry0, rx1, ry1): does the trip meet the box in that time?"""
    window = _windowed(asked, temporal)
    spans = window.join(placed, "trip_id").where("c0 <= d2 AND d1 <= c1 AND x0 <= rx1 AND rx0 <= x1 AND y0 <= ry1 AND ry0 <= y1")
    met = _clipped(_open(spans, aux)).where("px0 <= rx1 AND rx0 <= px1 AND py0 <= ry1 AND ry0 <= py1").select("qid", "trip_id").distinct()
    return asked.select("qid", "trip_id").join(met.withColumn("_hit", F.lit(1)), ["qid", "trip_id"], "left").select("qid", "trip_id", F.coalesce("_hit", F.lit(0)).alias("hit"))


def passing_near(asked: DataFrame, temporal: DataFrame, placed: DataFrame, aux: Aux) -> DataFrame:
    """qid, trip_id of trips that come within ``reach`` of (x, y) between t1 and t2; q: qid, x, y, reach, t1, t2.

    Trips are found by the cells that their pieces' boxes touch; cells are as wide as the largest reach.
    """
    cell = asked.agg(F.greatest(F.max("reach"), F.lit(3000))).first()[0] or 3000
    cells = lambda lo, hi: F.sequence(F.floor(lo / cell), F.floor(hi / cell))
    point = asked.withColumn("cx", F.explode(cells(F.col("x") - F.col("reach"), F.col("x") + F.col("reach")))).withColumn("cy", F.explode(cells(F.col("y") - F.col("reach"), F.col("y") + F.col("reach"))))
    tiled = placed.withColumn("cx", F.explode(cells(F.col("x0"), F.col("x1")))).withColumn("cy", F.explode(cells(F.col("y0"), F.col("y1"))))
    close = point.join(tiled, ["cx", "cy"]).drop("cx", "cy").distinct()
    gap = lambda box: box_gap_squared(box, (F.col("x"), F.col("y"), F.col("x"), F.col("y"))) <= F.col("reach") * F.col("reach")
    boxed = close.where(gap(tuple(F.col(c) for c in ("x0", "y0", "x1", "y1"))))
    timed = _windowed(boxed, temporal.where(F.size("temporal") > 0)).join(temporal.select("trip_id", F.col("temporal")[0]["t"].alias("t_first"), F.element_at("temporal", -1)["t"].alias("t_last")), "trip_id")
    alive = timed.where("t1 <= t_last AND t_first <= t2 AND c0 <= d2 AND d1 <= c1")
    return _clipped(_open(alive, aux)).where(gap(tuple(F.col(c) for c in ("px0", "py0", "px1", "py1")))).select("qid", "trip_id").distinct()


_BOX = ("x0", "y0", "x1", "y1")


def _closest(met: DataFrame) -> DataFrame:
    """The rows (trip_a, trip_b and both boxes) that may hold the least distance: their lower bound is no more than the least upper bound of their pair."""
    low = box_gap_squared(tuple(F.col(f"a{c}") for c in _BOX), tuple(F.col(f"b{c}") for c in _BOX))
    far_x = F.greatest(F.col("ax1") - F.col("bx0"), F.col("bx1") - F.col("ax0"))
    far_y = F.greatest(F.col("ay1") - F.col("by0"), F.col("by1") - F.col("ay0"))
    bounds = met.withColumns({"low": low, "high": far_x * far_x + far_y * far_y})
    return bounds.withColumn("best", F.min("high").over(Window.partitionBy("trip_a", "trip_b"))).where("low <= best").drop("low", "high", "best", *[f"{s}{c}" for s in "ab" for c in _BOX])


def min_distance(pairs: DataFrame, placed: DataFrame, aux: Aux, stretch: int = 8) -> DataFrame:
    """trip_a, trip_b, d2: squared least distance between the paths of trip pairs; exact whatever the temporal bounds.

    Boxes of stretches of ``stretch`` pieces are compared first, then those of the
    pieces of the stretches that are left, then edges: so most pairs of pieces are
    never formed, and few are opened.
    """
    chunked = placed.withColumn("chunk", F.floor(F.col("k") / (2 * stretch)))
    boxes = [F.min("x0").alias("x0"), F.min("y0").alias("y0"), F.max("x1").alias("x1"), F.max("y1").alias("y1")]
    wide, narrow = chunked.groupBy("trip_id", "chunk").agg(*boxes), chunked.select("trip_id", "chunk", "span", *_BOX).distinct()
    side = lambda df, s: df.select(*[F.col(c).alias(f"{c.removesuffix('_id')}_{s}" if c not in _BOX else f"{s}{c}") for c in df.columns])
    near = _closest(pairs.select("trip_a", "trip_b").join(side(wide, "a"), "trip_a").join(side(wide, "b"), "trip_b"))
    kept = _closest(near.join(side(narrow, "a"), ["trip_a", "chunk_a"]).join(side(narrow, "b"), ["trip_b", "chunk_b"])).select("trip_a", "trip_b", "span_a", "span_b").distinct()
    part = lambda s: aux.parts.select(F.col("span").alias(f"span_{s}"), *[f(a, b).alias(f"{s}{n}") for n, f, a, b in (("x0", F.least, "x0", "x1"), ("y0", F.least, "y0", "y1"), ("x1", F.greatest, "x0", "x1"), ("y1", F.greatest, "y0", "y1"))])
    opened = kept.join(part("a"), "span_a").join(part("b"), "span_b")
    return opened.groupBy("trip_a", "trip_b").agg(F.min(box_gap_squared(tuple(F.col(f"a{c}") for c in _BOX), tuple(F.col(f"b{c}") for c in _BOX))).cast("long").alias("d2"))


def shelved(placed: DataFrame) -> DataFrame:
    """trip_id, shelf: one row for each trip, its pieces in order as an array of (c1, span), for answers that need one piece of a trip."""
    return placed.groupBy("trip_id").agg(F.sort_array(F.collect_list(F.struct("c1", "span"))).alias("shelf"))


def where_on_shelf(asked: DataFrame, trips: DataFrame, aux: Aux) -> DataFrame:
    """As ``where_at``, from rows (trip_id, temporal, shelf): two joins by key, one piece of a trip opened, nothing exploded."""
    d = asked.join(trips, "trip_id").withColumn("d", F.expr(dis_sql("temporal", "t")).cast("long"))
    d = d.withColumn("total", F.expr("element_at(shelf, -1).c1")).withColumns({"look": F.least("d", F.col("total") - 1), "d": F.least("d", "total")})
    # Running lengths ascend, so the first one above the distance is that of the piece.
    at = d.withColumn("_i", F.expr("size(filter(shelf, s -> s.c1 <= look))")).select("qid", "trip_id", "d", "look", F.expr("shelf[_i].span").alias("span"), F.expr("IF(_i = 0, 0L, shelf[_i - 1].c1)").alias("c0"))
    edge = _open(at, aux).where("at <= look AND look < at + w").withColumn("part", F.col("d") - F.col("at"))
    return edge.select("qid", "trip_id", along("ex0", "ex1", "part", "w").alias("x"), along("ey0", "ey1", "part", "w").alias("y"))


def edge_counts(spans: DataFrame, aux: Aux) -> DataFrame:
    """e, n: how often each edge is driven; every distinct piece and hop is opened once, with its count."""
    return spans.groupBy("span").agg(F.count(F.lit(1)).alias("times")).join(aux.parts.select("span", "e"), "span").groupBy("e").agg(F.sum("times").cast("long").alias("n"))


def snapshot(temporal: DataFrame, placed: DataFrame, aux: Aux, t: int, cell: int) -> DataFrame:
    """cx, cy, n: trips under way in each cell at a time."""
    under = temporal.where((F.col("temporal")[0]["t"] <= t) & (F.element_at("temporal", -1)["t"] >= t))
    at = where_at(under.select(F.col("trip_id").alias("qid"), "trip_id", F.lit(t).cast("long").alias("t")), under, placed, aux)
    return at.groupBy(F.floor(F.col("x") / cell).alias("cx"), F.floor(F.col("y") / cell).alias("cy")).agg(F.count(F.lit(1)).alias("n"))


def dense_clusters(cells: DataFrame, least: int) -> DataFrame:
    """t, cluster, cells, trips: cells (t, cx, cy, n) with ``least`` trips or more, joined where they touch, corners included."""
    from roadtraj.plans.graph import components

    name = lambda x, y: F.concat_ws(":", "t", x, y)
    dense = cells.where(F.col("n") >= least).withColumn("node", name("cx", "cy"))
    ahead = F.explode(F.array(*[F.struct(F.lit(dx).alias("x"), F.lit(dy).alias("y")) for dx, dy in ((0, 0), (1, 0), (0, 1), (1, 1), (1, -1))]))
    near = dense.withColumn("_d", ahead).select(F.col("node").alias("a"), name(F.col("cx") + F.col("_d.x"), F.col("cy") + F.col("_d.y")).alias("b"))
    labels = components(near.join(dense.select(F.col("node").alias("b")), "b").select("a", "b"))
    joined = dense.join(labels, "node", "left").withColumn("label", F.coalesce("label", "node"))
    named = joined.groupBy("t", "label").agg(F.min("node").alias("cluster"), F.count(F.lit(1)).alias("cells"), F.sum("n").alias("trips"))
    return named.select("t", "cluster", "cells", "trips")


def region_trips(asked: DataFrame, index: DataFrame, cell: int, temporal: DataFrame, placed: DataFrame, aux: Aux) -> DataFrame:
    """rid, trip_id of trips that meet a box between t1 and t2; q: rid, t1, t2, rx0, ry0, rx1, ry1.

    The cell index (see ``cell_index``) names the trips whose boxes touch the cells of
    a box, trips not under way are dropped, and only the rest is opened.
    """
    span = lambda lo, hi: F.explode(F.sequence(F.floor(F.col(lo) / cell), F.floor(F.col(hi) / cell)))
    # A box is cut to the index's extent first, so a strip without ends has a bounded number of cells.
    extent = index.agg(F.min("cx").alias("ax"), F.max("cx").alias("bx"), F.min("cy").alias("ay"), F.max("cy").alias("by"))
    cut_ = asked.crossJoin(F.broadcast(extent)).select("rid", F.greatest(F.col("rx0"), F.col("ax") * cell).alias("lx"), F.least(F.col("rx1"), F.col("bx") * cell + cell - 1).alias("hx"), F.greatest(F.col("ry0"), F.col("ay") * cell).alias("ly"), F.least(F.col("ry1"), F.col("by") * cell + cell - 1).alias("hy")).where("lx <= hx AND ly <= hy")
    tiled = cut_.withColumn("cx", span("lx", "hx")).withColumn("cy", span("ly", "hy"))
    near = tiled.join(index, ["cx", "cy"]).select("rid", "trip_id").distinct()
    ends = temporal.where(F.size("temporal") > 0).select("trip_id", F.col("temporal")[0]["t"].alias("_a"), F.element_at("temporal", -1)["t"].alias("_b"))
    alive = near.join(asked, "rid").join(ends, "trip_id").where("_a <= t2 AND t1 <= _b").drop("_a", "_b").withColumnRenamed("rid", "qid")
    return range_hit(alive, temporal, placed, aux).where("hit = 1").select(F.col("qid").alias("rid"), "trip_id")


def visited(asked: DataFrame, temporal: DataFrame, placed: DataFrame) -> DataFrame:
    """qid, tuples, spans: sequence entries and pieces passed before a where_at answer is found."""
    d = asked.join(temporal, "trip_id").select("qid", "trip_id", F.expr("size(filter(temporal, p -> p.t < t))").alias("tuples"), F.expr(dis_sql("temporal", "t")).cast("long").alias("d"))
    return d.join(placed, "trip_id").where("c0 <= d").groupBy("qid", "tuples").agg(F.count(F.lit(1)).alias("spans"))


def cell_index(placed: DataFrame, cell: int) -> DataFrame:
    """cx, cy, trip_id: the cells that each trip's boxes touch."""
    tiled = placed.withColumn("cx", F.explode(F.sequence(F.floor(F.col("x0") / cell), F.floor(F.col("x1") / cell)))).withColumn("cy", F.explode(F.sequence(F.floor(F.col("y0") / cell), F.floor(F.col("y1") / cell))))
    return tiled.select("cx", "cy", "trip_id").distinct()
