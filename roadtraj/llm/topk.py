"""Exact top-k search by exhaustive term-at-a-time accumulation.

Vectors become integer rows whose dimensions are the terms. Candidates are
packed into blocks that hold, for each dimension, the posting column of all
their rows. A block of queries goes through the dimensions one at a time: each
query row with a non-zero weight adds weight times posting to its dense array
of scores. The k best of an array are selected per block and merged by query.

Query blocks and strips of candidate blocks span a grid. A cell is a join key: a query
block goes to every strip and a candidate block to every query block, so each
pair meets in one cell, a task scores a few cells, and cells outnumber cores long
before a table is large.

Defined results: a vector that is null or holds a null or non-finite component
takes no part; vectors of different lengths are scored over the dimensions both
have; a row is no candidate for queries of its own vec_id; a null vec_id takes
no part; repeated rows are candidates of their own, and of the rows of one
vec_id that ask, the smallest vector does; ties go to the smaller vec_id.
Components beyond the range of bigint count as its ends, and so do scores, which
are added up without a bound where they could pass it.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

ROWS_PER_BLOCK = 4096
QUERIES_PER_BLOCK = 512
_PACKED = pa.schema([("ids", pa.binary()), ("dims", pa.int32()), ("postings", pa.binary())])
_FOUND = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.int64())])


def integer_vectors(vectors: DataFrame, scale: int = 256) -> DataFrame:
    """vec_id, weights array<bigint>: floor(scale * x) of usable vectors."""
    whole = F.expr("forall(embedding, x -> x IS NOT NULL AND NOT isnan(x) AND abs(x) < double('Infinity'))")
    usable = vectors.where(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & whole)
    return usable.select(F.col("vec_id").cast("long"), F.expr(f"transform(embedding, x -> cast(floor({scale}.0D * double(x)) as bigint))").alias("weights"))


def _pack(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[pa.RecordBatch]:
    held: dict[int, list] = {}

    def emit(dims, parts):
        ids, block = np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])
        return pa.RecordBatch.from_arrays([pa.array([ids.tobytes()], pa.binary()), pa.array([dims], pa.int32()), pa.array([np.ascontiguousarray(block.T).tobytes()], pa.binary())], schema=_PACKED)

    for batch in batches:
        column = batch.column("weights")
        lengths = np.diff(np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1]) if len(column) else np.zeros(0, np.int32)
        values, ids = column.flatten().to_numpy(zero_copy_only=False), batch.column("vec_id").to_numpy(zero_copy_only=False)
        stops = np.concatenate([[0], np.cumsum(lengths)])
        for dims in np.unique(lengths):
            at = np.flatnonzero(lengths == dims)
            block = values[(stops[at][:, None] + np.arange(dims)).astype(np.int64)] if dims else np.zeros((len(at), 0), np.int64)
            for lo in range(0, len(at), rows):
                parts = held.setdefault(int(dims), [])
                parts.append((ids[at[lo : lo + rows]], block[lo : lo + rows]))
                if sum(len(p[0]) for p in parts) >= rows:
                    yield emit(int(dims), held.pop(int(dims)))
    for dims, parts in held.items():
        yield emit(dims, parts)


def pack(vectors: DataFrame, rows: int) -> DataFrame:
    """Blocks of about ``rows`` vectors of one length: ids, dims, postings (dimension by dimension)."""
    return vectors.mapInArrow(lambda batches: _pack(batches, rows), "ids binary, dims int, postings binary")


def accumulate(weights: np.ndarray, postings: np.ndarray) -> np.ndarray:
    """Dense scores (queries x rows): one dimension's postings at a time, scattered by non-zero weights."""
    dims = min(weights.shape[1], postings.shape[0])
    most = dims * float(np.abs(weights.astype(np.float64)).max(initial=0)) * float(np.abs(postings.astype(np.float64)).max(initial=0))
    kind = np.int64 if most < 2.0**62 else object
    weights, postings = weights.astype(kind, copy=False), postings.astype(kind, copy=False)
    scores = np.zeros((weights.shape[0], postings.shape[1]), kind)
    for d in range(dims):
        at = np.flatnonzero(weights[:, d])
        if len(at) == len(scores):
            scores += weights[:, d, None] * postings[d]
        elif len(at):
            scores[at] += weights[at, d, None] * postings[d]
    return scores if kind is np.int64 else np.clip(scores, -(2**63), 2**63 - 1).astype(np.int64)


def best(query: int, ids: np.ndarray, scores: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """The k highest scores of other ids; ties to the smaller id."""
    other = np.flatnonzero(ids != query)
    if len(other) > k:
        bound = np.partition(scores[other], len(other) - k)[len(other) - k]
        other = other[scores[other] >= bound]
    order = np.lexsort((ids[other], -scores[other]))[:k]
    return ids[other][order], scores[other][order]


def _score(batches: Iterator[pa.RecordBatch], k: int, queries_at_once: int = 64) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for row in batch.to_pylist():
            ids, query_ids = np.frombuffer(row["ids"], np.int64), np.frombuffer(row["q_ids"], np.int64)
            postings = np.frombuffer(row["postings"], np.int64).reshape(row["dims"], len(ids))
            weights = np.ascontiguousarray(np.frombuffer(row["q_postings"], np.int64).reshape(row["q_dims"], len(query_ids)).T)
            out = []
            for lo in range(0, len(query_ids), queries_at_once):
                scores = accumulate(weights[lo : lo + queries_at_once], postings)
                for query, line in zip(query_ids[lo : lo + queries_at_once], scores, strict=True):
                    found, values = best(query, ids, line, k)
                    out.append((np.full(len(found), query), found, values))
            columns = [np.concatenate([o[i] for o in out]) for i in range(3)]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], schema=_FOUND)


def top_k(vectors: DataFrame, k: int = 5, every: int = 50, scale: int = 256) -> DataFrame:
    """query_id, rank, vec_id, score of each query (vec_id divisible by ``every``) against all rows."""
    whole = integer_vectors(vectors, scale)
    queries = whole.where(F.col("vec_id") % every == 0).groupBy("vec_id").agg(F.min("weights").alias("weights"))
    sizes = whole.agg(F.count(F.lit(1)).alias("rows"), F.count_distinct(F.when(F.col("vec_id") % every == 0, F.col("vec_id"))).alias("asked")).first()
    parts, strips = max(1, -(-sizes["asked"] // QUERIES_PER_BLOCK)), max(1, -(-sizes["rows"] // ROWS_PER_BLOCK))
    cell = lambda n, name: F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias(name)
    asked = pack(queries.repartition(parts, "vec_id"), QUERIES_PER_BLOCK).withColumn("part", F.pmod(F.xxhash64("ids"), F.lit(parts)).cast("int"))
    asked = asked.select(F.col("ids").alias("q_ids"), F.col("dims").alias("q_dims"), F.col("postings").alias("q_postings"), "part", cell(strips, "strip"))
    given = pack(whole, ROWS_PER_BLOCK).withColumn("strip", F.pmod(F.xxhash64("ids"), F.lit(strips)).cast("int")).select("*", cell(parts, "part"))
    # As many partitions as cells, up to a bound, so that small blocks of much work are not merged into one task.
    tasks = min(parts * strips, max(vectors.sparkSession.sparkContext.defaultParallelism * 4, int(vectors.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    met = given.repartition(tasks, "part", "strip").hint("merge").join(asked.repartition(tasks, "part", "strip"), ["part", "strip"])
    found = met.mapInArrow(lambda batches: _score(batches, k), "query_id long, vec_id long, score long")
    # The limit on the rank reaches the tasks before the shuffle, which thus carries k rows for each query and task.
    place = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", place).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
