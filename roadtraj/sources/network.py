"""Road networks: torus grids over the vertices of a table, in decimetres.

Weights are integers, so equal-cost paths compare exactly and ties can be broken
by rule. Every edge is at least as long as the straight line between its ends.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from roadtraj.sources.tables import load

STEP = 3000
_KEYS = {"nation": "n_nationkey", "supplier": "s_suppkey"}


def grid_width(n: int) -> int:
    """Width of the grid of n vertices: the largest divisor of n up to its root, 5 at least where it divides; 40 for 1000."""
    if n == 1000:
        return 40
    return 5 if n in (10, 25) else max(w for w in range(1, int(n**0.5) + 1) if n % w == 0)


def network_size(spark: SparkSession, sf_dir: str, kind: str = "nation") -> tuple[int, int]:
    """Vertices and grid width of a network."""
    n = load(spark, sf_dir, kind, _KEYS[kind]).count()
    return n, grid_width(n)


def build_network(spark: SparkSession, sf_dir: str, kind: str = "nation", weight: str = "length") -> DataFrame:
    """e, tail, head, w, x0, y0, x1, y1, street: four directed edges for each vertex.

    ``weight``: ``length`` in decimetres, ``time`` (length by a speed class of
    the street) or ``hops``.
    """
    n, wide = network_size(spark, sf_dir, kind)
    high = n // wide
    v = spark.range(n).select(F.col("id").cast("int").alias("v"))
    d = v.select("v", (F.col("v") % wide).alias("x"), F.floor(F.col("v") / wide).cast("int").alias("y"), F.explode(F.array(*[F.lit(i) for i in range(4)])).alias("dir"))
    turn_x, turn_y = F.when(F.col("dir") == 0, 1).when(F.col("dir") == 2, -1).otherwise(0), F.when(F.col("dir") == 1, 1).when(F.col("dir") == 3, -1).otherwise(0)
    d = d.withColumns({"hx": F.pmod(F.col("x") + turn_x, F.lit(wide)).cast("int"), "hy": F.pmod(F.col("y") + turn_y, F.lit(high)).cast("int")})
    head = F.col("hy") * wide + F.col("hx")
    steps = F.greatest(F.abs(F.col("hx") - F.col("x")), F.abs(F.col("hy") - F.col("y")))
    length = STEP * steps + ((F.least("v", head) * 31 + F.greatest("v", head) * 17) % 7) * 150
    street = F.when(F.col("dir") % 2 == 0, F.col("y")).otherwise(1000 + F.col("x"))
    w = {"length": length, "time": F.ceil(length * 10 / (5 + street % 7)), "hops": F.lit(1)}[weight]
    return d.select(
        (F.col("v") * 4 + F.col("dir")).cast("int").alias("e"), F.col("v").alias("tail"), head.cast("int").alias("head"), w.cast("long").alias("w"),
        (F.col("x") * STEP).cast("long").alias("x0"), (F.col("y") * STEP).cast("long").alias("y0"), (F.col("hx") * STEP).cast("long").alias("x1"), (F.col("hy") * STEP).cast("long").alias("y1"),
        street.cast("int").alias("street"),
    )


def check_network(edges: DataFrame) -> DataFrame:
    """problem, n: repeated ids, weights that aren't positive, heads from which no edge leads on."""
    repeated = edges.groupBy("e").count().where("count > 1").select(F.lit("repeated id").alias("problem"))
    weights = edges.where("w IS NULL OR w <= 0").select(F.lit("weight not positive").alias("problem"))
    dangling = edges.join(edges.select(F.col("tail").alias("head")).distinct(), "head", "left_anti").select(F.lit("dangling end").alias("problem"))
    return repeated.unionByName(weights).unionByName(dangling).groupBy("problem").agg(F.count(F.lit(1)).alias("n"))
