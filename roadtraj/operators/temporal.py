"""Error-bounded temporal codec and its measures, exact in integers.

From the last kept point (the anchor) a skipped point at (dd, dt) allows the
slopes between (dd - tau) / dt and (dd + tau) / dt, and between dd / (dt + eta)
and, where dt > eta, dd / (dt - eta). The codec carries the range that all
skipped points allow as two fractions; a point outside of it ends the run, the
point before is kept, and the range starts anew from the constraint of the point
at hand. The last point is always kept. The opening window baseline tests every
skipped point again at each step instead.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from roadtraj.functions.interpolate import dis_sql, tim_sql

POINTS = "array<struct<d: bigint, t: bigint>>"


# A slope is a fraction of differences, and slopes are compared by cross products. Where the extent of a
# sequence shows that those fit into 64 bits they are BIGINT, else DECIMAL, exact up to 38 digits.
_BIG, _WIDE = "BIGINT", "DECIMAL(19, 0)"


def _difference(a: str, b: str, kind: str) -> str:
    return f"({a} - {b})" if kind == _BIG else f"cast(cast({a} as {_WIDE}) - {b} as {_WIDE})"


def _fraction(n: str, m: str, kind: str) -> str:
    return f"named_struct('n', cast({n} as {kind}), 'm', cast({m} as {kind}))"


def _narrowest(bounds: list[str], start: str, less: bool) -> str:
    """SQL: the greatest (least) of fractions and ``start``."""
    if not bounds:
        return start
    return f"aggregate(array({', '.join(bounds)}), {start}, (_b, _c) -> IF(_c.n * _b.m {'<' if less else '>'} _b.n * _c.m, _c, _b))"


def _lower(dd: str, dt: str, tau: int | None, eta: int | None, start: str, kind: str) -> str:
    return _narrowest(([] if tau is None else [_fraction(f"{dd} - {tau}", dt, kind)]) + ([] if eta is None else [_fraction(dd, f"{dt} + {eta}", kind)]), start, False)


def _upper(dd: str, dt: str, tau: int | None, eta: int | None, start: str, kind: str) -> str:
    late = [] if eta is None else [f"IF({dt} > {eta}, {_fraction(dd, f'{dt} - {eta}', kind)}, {start})"]
    return _narrowest(([] if tau is None else [_fraction(f"{dd} + {tau}", dt, kind)]) + late, start, True)


def _fits(column: str, tau: int | None, eta: int | None) -> str:
    """SQL: no cross product of a sequence's slopes passes 64 bits."""
    span = lambda c, b: f"(double(element_at({column}, -1).{c}) - {column}[0].{c} + double({0 if b is None else b}))"
    return f"{span('d', tau)} * {span('t', eta)} < 4.0E18D"


def _fold(tau: int | None, eta: int | None, column: str, begin: str, keep: str, finish: str, kind: str) -> str:
    dd, dt = _difference("p.d", "a.from.d", kind), _difference("p.t", "a.from.t", kind)
    again_d, again_t = _difference("p.d", "a.prev.d", kind), _difference("p.t", "a.prev.t", kind)
    zero, free = _fraction("0", "1", kind), _fraction("1", "0", kind)
    inside = f"{dd} * a.lo.m >= a.lo.n * {dt} AND {dd} * a.hi.m <= a.hi.n * {dt}"
    go = f"named_struct('from', a.from, 'prev', p, 'lo', {_lower(dd, dt, tau, eta, 'a.lo', kind)}, 'hi', {_upper(dd, dt, tau, eta, 'a.hi', kind)}, 'out', a.out)"
    restart = f"named_struct('from', a.prev, 'prev', p, 'lo', {_lower(again_d, again_t, tau, eta, zero, kind)}, 'hi', {_upper(again_d, again_t, tau, eta, free, kind)}, 'out', {keep})"
    start = f"named_struct('from', {column}[0], 'prev', {column}[0], 'lo', {zero}, 'hi', {free}, 'out', {begin})"
    return f"aggregate(slice({column}, 2, size({column})), {start}, (a, p) -> IF({inside}, {go}, {restart}), a -> {finish})"


def _run(tau: int | None, eta: int | None, column: str, few: str, begin: str, keep: str, finish: str) -> str:
    """SQL: a fold over an array of (d, t) whose output starts with ``begin``, grows by ``keep`` and ends with ``finish``; ``few`` for two points or less."""
    folds = [_fold(tau, eta, column, begin, keep, finish, kind) for kind in (_BIG, _WIDE)]
    return f"CASE WHEN size({column}) <= 2 THEN {few} WHEN {_fits(column, tau, eta)} THEN {folds[0]} ELSE {folds[1]} END"


def angular(tau: int | None, eta: int | None, column: str = "temporal") -> str:
    """SQL: the kept points of an array of (d, t); None is no bound. Row-local; the state is constant but for the output."""
    return _run(tau, eta, column, column, f"array({column}[0])", "concat(a.out, array(a.prev))", "concat(a.out, array(a.prev))")


def angular_count(tau: int | str | None, eta: int | str | None, column: str = "temporal") -> str:
    """SQL: how many points ``angular`` keeps, without making their array. Bounds are numbers, columns, or None."""
    return _run(tau, eta, column, f"size({column})", "1", "a.out + 1", "a.out + 1")


def narrow(low: tuple, high: tuple, dd: int, dt: int, tau: int | None, eta: int | None) -> tuple[tuple, tuple]:
    """The range of slopes, as fractions, that one more skipped point allows."""
    lower = ([] if tau is None else [(dd - tau, dt)]) + ([] if eta is None else [(dd, dt + eta)])
    upper = ([] if tau is None else [(dd + tau, dt)]) + ([] if eta is None or dt <= eta else [(dd, dt - eta)])
    for n, m in lower:
        if n * low[1] > low[0] * m:
            low = (n, m)
    for n, m in upper:
        if n * high[1] < high[0] * m:
            high = (n, m)
    return low, high


def compress_points(points: list[dict], tau: int | None, eta: int | None) -> list[dict]:
    """The same codec for one long sequence, in one pass over a list."""
    if len(points) <= 2:
        return points
    out, anchor, prev = [points[0]], points[0], points[0]
    lo, hi = (0, 1), (1, 0)
    for p in points[1:]:
        dd, dt = p["d"] - anchor["d"], p["t"] - anchor["t"]
        if dd * lo[1] >= lo[0] * dt and dd * hi[1] <= hi[0] * dt:
            lo, hi = narrow(lo, hi, dd, dt, tau, eta)
        else:
            out.append(prev)
            anchor = prev
            lo, hi = narrow((0, 1), (1, 0), p["d"] - anchor["d"], p["t"] - anchor["t"], tau, eta)
        prev = p
    return [*out, prev]


def temporal_compress(df: DataFrame, tau: int | None, eta: int | None, column: str = "temporal", strategy: str = "native") -> DataFrame:
    """``column`` thinned. ``strategy``: native (an array fold in the JVM) or arrow (for very long sequences)."""
    if strategy == "native":
        return df.withColumn(column, F.expr(angular(tau, eta, column)))
    kind = pa.list_(pa.struct([("d", pa.int64()), ("t", pa.int64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            done = pa.array([compress_points(p, tau, eta) for p in batch.column(column).to_pylist()], kind)
            yield pa.RecordBatch.from_arrays([done if n == column else batch.column(n) for n in batch.schema.names], names=batch.schema.names)

    return df.mapInArrow(run, ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema))


def temporal_decompress(df: DataFrame) -> DataFrame:
    """A thinned sequence is a sequence: nothing to do."""
    return df


def opening_window(df: DataFrame, tau: int, eta: int | None, column: str = "temporal") -> DataFrame:
    """The quadratic baseline: a point joins the window only if every skipped point allows its slope."""
    s = f"{column}[i - 1]"
    dd, dt = f"({s}.d - a.from.d)", f"({s}.t - a.from.t)"
    fits = (
        f"forall(slice({column}, a.at + 1, i - a.at - 1), q -> "
        f"{dd} * (q.t - a.from.t) >= ((q.d - a.from.d) - {tau}L) * {dt} AND {dd} * (q.t - a.from.t) <= ((q.d - a.from.d) + {tau}L) * {dt} "
        + ("" if eta is None else f"AND {dd} * ((q.t - a.from.t) + {eta}L) >= (q.d - a.from.d) * {dt} AND ((q.t - a.from.t) <= {eta}L OR {dd} * ((q.t - a.from.t) - {eta}L) <= (q.d - a.from.d) * {dt})")
        + ")"
    )
    step = f"IF({fits}, a, named_struct('from', {column}[i - 2], 'at', i - 1, 'out', concat(a.out, array({column}[i - 2]))))"
    fold = f"aggregate(sequence(2, size({column})), named_struct('from', {column}[0], 'at', 1, 'out', array({column}[0])), (a, i) -> {step}, a -> concat(a.out, array({column}[size({column}) - 1])))"
    return df.withColumn(column, F.expr(f"CASE WHEN size({column}) <= 2 THEN {column} ELSE {fold} END"))


def opening_window_xyt(df: DataFrame, eps: int, column: str = "samples") -> DataFrame:
    """The opening window on plane samples (x, y, t): every skipped point within eps of the straight move at its time."""
    s = f"{column}[i - 1]"
    part = f"(double(q.t - a.from.t) / ({s}.t - a.from.t))"
    gap = lambda c: f"(a.from.{c} + ({s}.{c} - a.from.{c}) * {part} - q.{c})"
    fits = f"forall(slice({column}, a.at + 1, i - a.at - 1), q -> {gap('x')} * {gap('x')} + {gap('y')} * {gap('y')} <= double({eps}) * {eps})"
    step = f"IF({fits}, a, named_struct('from', {column}[i - 2], 'at', i - 1, 'out', concat(a.out, array({column}[i - 2]))))"
    fold = f"aggregate(sequence(2, size({column})), named_struct('from', {column}[0], 'at', 1, 'out', array({column}[0])), (a, i) -> {step}, a -> concat(a.out, array({column}[size({column}) - 1])))"
    return df.withColumn(column, F.expr(f"CASE WHEN size({column}) <= 2 THEN {column} ELSE {fold} END"))


def angular_range(points: DataFrame, tau: int, eta: int) -> DataFrame:
    """trip_id, lo, hi (slopes in parts per million, rounded down): what all later points allow from the first point.

    The set version is a plain aggregate: the largest lower and smallest upper bound.
    """
    first = points.groupBy("trip_id").agg(F.min(F.struct("t", "d")).alias("p"))
    rel = points.join(first, "trip_id").select("trip_id", (F.col("d") - F.col("p.d")).alias("dd"), (F.col("t") - F.col("p.t")).alias("dt")).where("dt > 0")
    lo = F.greatest(F.expr(f"floor((dd - {tau}L) * 1000000 / dt)"), F.expr(f"floor(dd * 1000000 / (dt + {eta}L))"))
    hi = F.least(F.expr(f"floor((dd + {tau}L) * 1000000 / dt)"), F.when(F.col("dt") > eta, F.expr(f"floor(dd * 1000000 / (dt - {eta}L))")))
    return rel.groupBy("trip_id").agg(F.greatest(F.max(lo), F.lit(0)).cast("long").alias("lo"), F.min(hi).cast("long").alias("hi"))


def tsnd(pair: DataFrame, original: str = "temporal", packed: str = "packed") -> DataFrame:
    """Adds tsnd: the largest distance between both sequences at the same time; it is attained at original points."""
    return pair.withColumn("tsnd", F.expr(f"array_max(transform({original}, p -> abs(p.d - {dis_sql(packed, 'p.t')})))").cast("long"))


def nstd(pair: DataFrame, original: str = "temporal", packed: str = "packed") -> DataFrame:
    """Adds nstd: the largest time between both at the same distance; a stop is the interval of its times."""
    gap = f"greatest(0L, p.t - {tim_sql(packed, 'p.d', True)}, {tim_sql(packed, 'p.d')} - p.t)"
    return pair.withColumn("nstd", F.expr(f"array_max(transform({original}, p -> {gap}))").cast("long"))


def stationary(points: DataFrame) -> DataFrame:
    """trip_id, t_from, t_to: maximal spans without movement."""
    from pyspark.sql import Window

    by = Window.partitionBy("trip_id").orderBy("t")
    moved = points.withColumn("new", F.coalesce((F.col("d") != F.lag("d").over(by)).cast("int"), F.lit(0)))
    runs = moved.withColumn("run", F.sum("new").over(by))
    return runs.groupBy("trip_id", "run").agg(F.min("t").alias("t_from"), F.max("t").alias("t_to"), F.count(F.lit(1)).alias("n")).where("n > 1").select("trip_id", "t_from", "t_to")
