"""Both spatial stages in one pass over the trips: skip, tile and pack; unpack and restore.

Tables of the network and the dictionary go to the tasks once; trips are never
shuffled.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from roadtraj.operators.flat import flatten, lists, map_column
from roadtraj.operators.grams import _BITS, TILINGS, _bits_struct, _checked, _unpacked
from roadtraj.operators.huffman import Codebook
from roadtraj.operators.spatial import RecordedPaths, restore, skip


def pack_paths(column: pa.Array, pairs: RecordedPaths | None, book: Codebook, how: str = "backward") -> pa.Array:
    """bits and n_bits of a column of paths; without the first stage where ``pairs`` is None."""
    short = column if pairs is None else skip(column, pairs)
    return _bits_struct(*TILINGS[how](*_checked(*flatten(short), book), book), book, column)


def unpack_paths(coded: pa.Array, pairs: RecordedPaths | None, book: Codebook) -> pa.Array:
    edges, offsets = book.expand(*_unpacked(coded, book))
    short = lists(edges, offsets, pa.int32(), coded.field("bits"))
    return short if pairs is None else restore(short, pairs)


def compress_paths(paths: DataFrame, pairs: RecordedPaths | None, book: Codebook, how: str = "backward") -> DataFrame:
    """``path`` becomes bits and n_bits."""
    shared = paths.sparkSession.sparkContext.broadcast((pairs, book))
    packed = map_column(paths, "path", shared, lambda column, both: pack_paths(column, *both, how), _BITS)
    return packed.withColumns({"bits": F.col("path.bits"), "n_bits": F.col("path.n_bits")}).drop("path")


def decompress_paths(packed: DataFrame, pairs: RecordedPaths | None, book: Codebook) -> DataFrame:
    """bits and n_bits become ``path`` again."""
    shared = packed.sparkSession.sparkContext.broadcast((pairs, book))
    whole = packed.withColumn("path", F.struct("bits", F.col("n_bits").cast("long").alias("n_bits"))).drop("bits", "n_bits")
    return map_column(whole, "path", shared, lambda column, both: unpack_paths(column, *both), "array<int>")
