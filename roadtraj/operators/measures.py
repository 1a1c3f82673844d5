"""Ratios, errors and sizes. Storage models are parameters, printed with every ratio."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from roadtraj.operators.spatial import TreeTable


@dataclass(frozen=True)
class StorageModel:
    """Bits of a sample (x, y, t), an edge id and a (d, t) pair."""

    xyt_bits: int = 192
    edge_bits: int = 32
    tuple_bits: int = 128


def ratio_rows(raw_points: int, edges: int, sp_edges: int, bits: int, kept: int, model: StorageModel = StorageModel()) -> list[tuple[str, int, int]]:
    """(stage, bits before, bits after) of every stage and of the whole."""
    return [
        ("shortest_path", edges * model.edge_bits, sp_edges * model.edge_bits),
        ("gram_coding", sp_edges * model.edge_bits, bits),
        ("spatial", edges * model.edge_bits, bits),
        ("temporal", raw_points * model.tuple_bits, kept * model.tuple_bits),
        ("overall", raw_points * model.xyt_bits, bits + kept * model.tuple_bits),
    ]


def range_accuracy(raw: DataFrame, packed: DataFrame) -> DataFrame:
    """raw_hit, packed_hit, n: how range answers on packed trips compare with those on raw trips."""
    return raw.withColumnRenamed("hit", "raw_hit").join(packed.withColumnRenamed("hit", "packed_hit"), ["qid", "trip_id"]).groupBy("raw_hit", "packed_hit").agg(F.count(F.lit(1)).alias("n"))


def error_summary(errors: DataFrame, column: str) -> DataFrame:
    """Largest, mean (rounded down) and 95th percentile of an error column."""
    return errors.agg(F.max(column).alias("largest"), F.floor(F.avg(column)).alias("mean"), F.expr(f"percentile({column}, 0.95)").cast("long").alias("p95"))


def tsed_squared(original_xyt: DataFrame, packed_xyt: DataFrame) -> DataFrame:
    """trip_id, tsed2: largest squared plane distance at equal times, over original sample times."""
    other = packed_xyt.select("trip_id", "seq", F.col("x").alias("px"), F.col("y").alias("py"))
    gap = (F.col("x") - F.col("px")) * (F.col("x") - F.col("px")) + (F.col("y") - F.col("py")) * (F.col("y") - F.col("py"))
    return original_xyt.join(other, ["trip_id", "seq"]).groupBy("trip_id").agg(F.max(gap).cast("long").alias("tsed2"))


def aux_sizes(sp: DataFrame | TreeTable, grams: DataFrame) -> DataFrame:
    """structure, entries, bytes: what the codec (pairs, automaton, codes) and the queries (distances, boxes) keep beside the trips.

    Bytes are those of the arrays: a pair is two vertices and an edge, a gram its
    text, links and symbol, a length eight bytes and a box four times eight.
    """
    pairs = grams.sparkSession.range(1).select(F.lit(sp.pairs).cast("long").alias("n")) if isinstance(sp, TreeTable) else sp.agg(F.count(F.lit(1)).alias("n"))
    coded = grams.agg(F.count(F.lit(1)).alias("n"), F.sum(F.octet_length("gram")).alias("text"))
    rows = [(pairs, "pair_last_edge", "n * 12"), (pairs, "pair_distance", "n * 8"), (pairs, "pair_box", "n * 32"), (coded, "automaton", "n * 16 + text"), (coded, "codes", "n * 16"), (coded, "gram_length", "n * 8"), (coded, "gram_box", "n * 32")]
    out = None
    for df, name, size in rows:
        row = df.select(F.lit(name).alias("structure"), F.col("n").alias("entries"), F.expr(size).cast("long").alias("bytes"))
        out = row if out is None else out.unionByName(row)
    return out


def match_accuracy(matched: DataFrame, truth: DataFrame) -> DataFrame:
    """n, right: fixes with a match, and those whose edge is the one driven."""
    return matched.withColumnRenamed("e", "found").join(truth.select("trip_id", "seq", "e"), ["trip_id", "seq"]).agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("found") == F.col("e")).cast("long")).alias("right"))


def check_dominance(network_gap: DataFrame, plane_gap: DataFrame, slack: int = 4) -> DataFrame:
    """trip_id, tsnd, tsed2 of trips whose plane distance exceeds the network distance: none where weights are at least straight lengths.

    ``slack`` covers positions that are rounded down.
    """
    return network_gap.join(plane_gap, "trip_id").where(F.col("tsed2") > (F.col("tsnd") + slack) * (F.col("tsnd") + slack)).select("trip_id", "tsnd", "tsed2")
