"""Distance at a time and time at a distance of a (d, t) sequence, in exact integers (rounded down).

Arguments are SQL fragments, so the same expression serves columns, lambda
variables and literals. Both search the array once; nothing leaves the JVM.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def dis_sql(temporal: str, t: str) -> str:
    """SQL: distance at time t; outside the sequence's time that of its nearer end."""
    i = f"size(filter({temporal}, _p -> _p.t < {t}))"
    inside = f"({temporal}[{i} - 1].d + ({temporal}[{i}].d - {temporal}[{i} - 1].d) * ({t} - {temporal}[{i} - 1].t) div ({temporal}[{i}].t - {temporal}[{i} - 1].t))"
    return f"(CASE WHEN {t} <= {temporal}[0].t THEN {temporal}[0].d WHEN {t} >= {temporal}[size({temporal}) - 1].t THEN {temporal}[size({temporal}) - 1].d ELSE {inside} END)"


def tim_sql(temporal: str, d: str, last: bool = False) -> str:
    """SQL: earliest (or latest) time at distance d; outside the sequence that of its nearer end."""
    if last:
        i = f"size(filter({temporal}, _p -> _p.d <= {d}))"
        inside = f"({temporal}[{i} - 1].t + ({temporal}[{i}].t - {temporal}[{i} - 1].t) * ({d} - {temporal}[{i} - 1].d) div ({temporal}[{i}].d - {temporal}[{i} - 1].d))"
        return f"(CASE WHEN {d} >= {temporal}[size({temporal}) - 1].d THEN {temporal}[size({temporal}) - 1].t WHEN {d} < {temporal}[0].d THEN {temporal}[0].t ELSE {inside} END)"
    i = f"size(filter({temporal}, _p -> _p.d < {d}))"
    inside = f"({temporal}[{i} - 1].t + ({temporal}[{i}].t - {temporal}[{i} - 1].t) * ({d} - {temporal}[{i} - 1].d) div ({temporal}[{i}].d - {temporal}[{i} - 1].d))"
    return f"(CASE WHEN {d} <= {temporal}[0].d THEN {temporal}[0].t WHEN {d} > {temporal}[size({temporal}) - 1].d THEN {temporal}[size({temporal}) - 1].t ELSE {inside} END)"


def dis(temporal: str, t: str) -> Column:
    return F.expr(dis_sql(temporal, t)).cast("long")


def tim(temporal: str, d: str, which: str = "first") -> Column:
    """``which``: first, last, or interval (a struct of both)."""
    if which == "interval":
        return F.struct(F.expr(tim_sql(temporal, d)).cast("long").alias("first"), F.expr(tim_sql(temporal, d, True)).cast("long").alias("last"))
    return F.expr(tim_sql(temporal, d, which == "last")).cast("long")


def avg_speed(temporal: str, t1: str, t2: str) -> Column:
    """Distance per million time units between two times, rounded down."""
    return F.expr(f"({dis_sql(temporal, t2)} - {dis_sql(temporal, t1)}) * 1000000 div ({t2} - {t1})").cast("long")
