"""The engine's functions under SQL names, for a session's queries over views."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from roadtraj.functions.interpolate import dis_sql, tim_sql

_SEQUENCE = "ARRAY<STRUCT<d: BIGINT, t: BIGINT>>"


class GramEdges:
    """pos, e of the edges of a gram."""

    def eval(self, gram: str):
        for pos, e in enumerate((gram or "").split("-"), 1):
            if e:
                yield pos, int(e)


def register(spark: SparkSession) -> None:
    """dis(temporal, t), tim(temporal, d), tim_last(temporal, d), piece_at(shelf, d), piece_start(shelf, d), along(c0, c1, part, w): plain SQL, inlined by the planner; gram_edges(gram): a table function.

    With views of trips (see ``packed.shelved``) and of a span's edges these answer where, when and range questions in SQL text.
    """
    for name, body in (("dis", dis_sql("temporal", "at")), ("tim", tim_sql("temporal", "at")), ("tim_last", tim_sql("temporal", "at", True))):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(temporal {_SEQUENCE}, at BIGINT) RETURNS BIGINT RETURN {body}")
    shelf = "ARRAY<STRUCT<c1: BIGINT, span: STRING>>"
    place = "size(filter(shelf, s -> s.c1 <= at))"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION piece_at(shelf {shelf}, at BIGINT) RETURNS STRING RETURN get(shelf, {place}).span")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION piece_start(shelf {shelf}, at BIGINT) RETURNS BIGINT RETURN IF({place} = 0, 0L, get(shelf, {place} - 1).c1)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION along(c0 BIGINT, c1 BIGINT, part BIGINT, w BIGINT) RETURNS BIGINT RETURN c0 + cast(floor((c1 - c0) * part / w) as bigint)")
    spark.udtf.register("gram_edges", udtf(GramEdges, returnType="pos int, e int"))
