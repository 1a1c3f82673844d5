"""Frequent sub-trajectories: n-grams up to a length, their links, matching, tiling and coding.

A gram is its edges joined by '-'. Counting one window at each start counts every
prefix of it, so counts are those of all n-grams; the set is closed under
sub-grams, so the longest dictionary gram that ends at a place is the state that
an automaton over the dictionary would be in, and a gram without its first edge
is its suffix link.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from roadtraj.operators.flat import alive, flatten, lists, map_column, offsets_of, steps
from roadtraj.operators.huffman import Codebook

THETA = 3


def explode_grams(paths: DataFrame, theta: int = THETA, column: str = "path", at: str = "start") -> DataFrame:
    """All other columns, pos (from 1), n, gram: one row for each gram that starts (or ends) at each place."""
    placed = paths.where(F.size(column) > 0).withColumn("pos", F.explode(F.sequence(F.lit(1), F.size(column))))
    room = (F.size(column) - F.col("pos") + 1) if at == "start" else F.col("pos")
    each = placed.withColumn("n", F.explode(F.sequence(F.lit(1), F.least(F.lit(theta), room))))
    first = F.col("pos") if at == "start" else F.col("pos") - F.col("n") + 1
    return each.withColumn("gram", F.array_join(F.slice(column, first, F.col("n")), "-")).drop(column)


def mine_grams(paths: DataFrame, theta: int = THETA, edges: DataFrame | None = None, min_freq: int = 1, column: str = "path") -> DataFrame:
    """gram, n, freq. Single edges of the network all stand in it, with frequency 0 if no path has them.

    ``min_freq`` drops rarer grams of two edges and more; what is left is still
    closed under sub-grams.
    """
    counted = explode_grams(paths.where(F.size(column) > 0).select(column), theta, column).groupBy("gram", "n").agg(F.count(F.lit(1)).alias("freq"))
    counted = counted.where((F.col("n") == 1) | (F.col("freq") >= min_freq)) if min_freq > 1 else counted
    if edges is None:
        return counted
    unseen = edges.select(F.col("e").cast("string").alias("gram")).join(counted.where("n = 1").select("gram"), "gram", "left_anti")
    return counted.unionByName(unseen.select("gram", F.lit(1).alias("n"), F.lit(0).cast("long").alias("freq")))


def link_grams(grams: DataFrame) -> DataFrame:
    """gram, n, freq, parent (without its last edge), suffix (without its first); null for single edges.

    Joins with the dictionary itself, so a link is there only where its gram is.
    """
    parent = F.when(F.col("n") > 1, F.regexp_replace("gram", "-[^-]*$", "")).alias("parent")
    suffix = F.when(F.col("n") > 1, F.regexp_replace("gram", "^[^-]*-", "")).alias("suffix")
    wanted = grams.select("gram", "n", "freq", parent, suffix)
    known = grams.select("gram")
    joined = wanted.join(known.withColumnRenamed("gram", "parent").withColumn("_p", F.lit(True)), "parent", "left").join(known.withColumnRenamed("gram", "suffix").withColumn("_s", F.lit(True)), "suffix", "left")
    return joined.select("gram", "n", "freq", F.when(F.col("_p"), F.col("parent")).alias("parent"), F.when(F.col("_s"), F.col("suffix")).alias("suffix"))


def match_lengths(paths: DataFrame, grams: DataFrame, theta: int = THETA, key: str = "trip_id") -> DataFrame:
    """key, pos, len: edges of the longest gram that ends at each place. A join; any dictionary size."""
    ending = explode_grams(paths.select(key, "path"), theta, "path", at="end")
    return ending.join(grams.select("gram"), "gram", "left_semi").groupBy(key, "pos").agg(F.max("n").alias("len"))


def tile(lengths: DataFrame, key: str = "trip_id") -> DataFrame:
    """key, pos, len of the pieces: from the end back, each takes the longest gram that ends there."""
    rows = lengths.groupBy(key).agg(F.sort_array(F.collect_list(F.struct("pos", "len")), asc=False).alias("s"))
    walk = (
        "aggregate(s, named_struct('left', 0, 'out', cast(array() as array<struct<pos: int, len: int>>)), (a, x) -> "
        "IF(a.left > 0, named_struct('left', a.left - 1, 'out', a.out), named_struct('left', x.len - 1, 'out', concat(a.out, array(x)))), a -> reverse(a.out))"
    )
    return rows.select(key, F.explode(F.expr(walk)).alias("p")).select(key, "p.pos", "p.len")


def _known(path: np.ndarray, offsets: np.ndarray, book: Codebook) -> np.ndarray:
    """Grams of 1 to theta edges that start at each place (theta x places), -1 where the dictionary has none."""
    stop = np.repeat(offsets[1:], np.diff(offsets))
    place = np.arange(len(path))
    out = np.full((book.theta, len(path)), -1, np.int64)
    here = place
    for n in range(book.theta):
        here = here[here + n < stop[here]]
        here = here if n == 0 else here[out[n - 1, here] >= 0]
        if not len(here):
            break
        out[n, here] = book.onward(out[n - 1, here] if n else np.full(len(here), -1), path[here + n].astype(np.int64))
    return out


def _jumps(size: np.ndarray, offsets: np.ndarray, backward: bool) -> np.ndarray:
    """Which places begin (backward: end) a piece, when every piece takes the size at its end that comes first. All rows jump at once."""
    mark = np.zeros(len(size), bool)
    own = np.flatnonzero(np.diff(offsets) > 0)
    at, low, high = (offsets[1:][own] - 1 if backward else offsets[:-1][own]), offsets[:-1][own], offsets[1:][own]
    while len(at):
        mark[at] = True
        at = at - size[at] if backward else at + size[at]
        more = (at >= low) & (at < high)
        at, low, high = at[more], low[more], high[more]
    return np.flatnonzero(mark)


def pieces_backward(path: np.ndarray, offsets: np.ndarray, book: Codebook) -> tuple[np.ndarray, np.ndarray]:
    """Pieces from the end back, each the longest gram that ends there: their grams, and the offsets of the rows."""
    known, size = _known(path, offsets, book), np.zeros(len(path), np.int64)
    for n in range(book.theta):
        at = np.flatnonzero(known[n] >= 0)
        size[at + n] = n + 1  # a longer gram comes later
    ends = _jumps(size, offsets, True)
    return known[size[ends] - 1, ends - size[ends] + 1], np.searchsorted(ends, offsets)


def pieces_forward(path: np.ndarray, offsets: np.ndarray, book: Codebook) -> tuple[np.ndarray, np.ndarray]:
    """Pieces from the front, each the longest gram that starts there."""
    known = _known(path, offsets, book)
    size = (known >= 0).sum(0)
    begins = _jumps(size, offsets, False)
    return known[size[begins] - 1, begins], np.searchsorted(begins, offsets)


def pieces_cheapest(path: np.ndarray, offsets: np.ndarray, book: Codebook) -> tuple[np.ndarray, np.ndarray]:
    """Pieces of least total code length, by dynamic programming over the last piece; of equals the shorter one."""
    known, stride = _known(path, offsets, book), len(path) + len(offsets)
    _, first, length = steps(offsets)
    row = np.searchsorted(offsets, first, side="right") - 1
    # Costs before and behind every place: one more than places in each row.
    cost, size = np.full(stride, np.iinfo(np.int64).max // 2), np.zeros(len(path), np.int64)
    cost[first + row] = 0
    for k in range(1, int(length.max(initial=0)) + 1):
        m = alive(length, k - 1)
        end, shift = first[:m] + k - 1, row[:m]
        for n in range(min(book.theta, k)):
            gram = known[n, end - n]
            through = np.where(gram >= 0, cost[end - n + shift] + book.bits[gram], np.iinfo(np.int64).max // 2)
            better = through < cost[end + 1 + shift]
            cost[(end + 1 + shift)[better]] = through[better]
            size[end[better]] = n + 1
    ends = _jumps(size, offsets, True)
    return known[size[ends] - 1, ends - size[ends] + 1], np.searchsorted(ends, offsets)


TILINGS = {"backward": pieces_backward, "forward": pieces_forward, "cheapest": pieces_cheapest}


def _checked(path: np.ndarray, offsets: np.ndarray, book: Codebook) -> tuple[np.ndarray, np.ndarray]:
    if len(path) and (book.onward(np.full(len(path), -1), path.astype(np.int64)) < 0).any():
        raise ValueError("an edge that the dictionary does not have; mine with the network's edges")
    return path, offsets


def decompose(paths: DataFrame, book: Codebook, how: str = "backward", column: str = "path") -> DataFrame:
    """``column`` becomes its pieces (array of grams). ``how``: backward, forward or cheapest."""
    tiling = TILINGS[how]

    def tile_column(column: pa.Array, book: Codebook) -> pa.Array:
        pieces, offsets = tiling(*_checked(*flatten(column), book), book)
        return lists(book.names.take(pa.array(pieces)), offsets, pa.string(), column)

    return map_column(paths, column, paths.sparkSession.sparkContext.broadcast(book), tile_column, "array<string>")


def _binary(data: np.ndarray, offsets: np.ndarray, like: pa.Array) -> pa.Array:
    whole = pa.Array.from_buffers(pa.binary(), len(offsets) - 1, [None, pa.py_buffer(offsets.astype(np.int32)), pa.py_buffer(np.ascontiguousarray(data))])
    return pc.if_else(like.is_null(), pa.scalar(None, pa.binary()), whole) if like.null_count else whole


def _bits_struct(grams: np.ndarray, offsets: np.ndarray, book: Codebook, like: pa.Array) -> pa.Array:
    data, bounds, n_bits = book.pack(grams, offsets)
    return pa.StructArray.from_arrays([_binary(data, bounds, like), pa.array(n_bits, pa.int64())], names=["bits", "n_bits"])


_BITS = "struct<bits: binary, n_bits: bigint>"


def encode(nodes: DataFrame, book: Codebook, column: str = "path") -> DataFrame:
    """Adds bits (binary) and n_bits; ``column`` holds pieces."""

    def pack_column(pieces: pa.Array, book: Codebook) -> pa.Array:
        lengths = pc.fill_null(pc.list_value_length(pieces), 0).to_numpy()
        grams = pc.index_in(pieces.flatten(), value_set=book.names)
        if grams.null_count:
            raise ValueError("a piece that is no gram of the dictionary")
        return _bits_struct(grams.to_numpy().astype(np.int64), offsets_of(lengths), book, pieces)

    packed = map_column(nodes.withColumn("_coded", F.col(column)), "_coded", nodes.sparkSession.sparkContext.broadcast(book), pack_column, _BITS)
    return packed.withColumns({"bits": F.col("_coded.bits"), "n_bits": F.col("_coded.n_bits")}).drop("_coded")


def _unpacked(coded: pa.Array, book: Codebook) -> tuple[np.ndarray, np.ndarray]:
    bits = pc.fill_null(coded.field("bits"), b"")
    offsets = np.frombuffer(bits.buffers()[1], np.int32)[bits.offset : bits.offset + len(bits) + 1].astype(np.int64)
    body = bits.buffers()[2]
    data = np.frombuffer(body, np.uint8)[offsets[0] : offsets[-1]] if body is not None and body.size else np.zeros(0, np.uint8)
    return book.unpack(data, offsets - offsets[0], pc.fill_null(coded.field("n_bits"), 0).to_numpy())


def decode(packed: DataFrame, book: Codebook) -> DataFrame:
    """bits, n_bits -> path array<int>, in place of bits."""

    def unpack_column(coded: pa.Array, book: Codebook) -> pa.Array:
        edges, offsets = book.expand(*_unpacked(coded, book))
        return lists(edges, offsets, pa.int32(), coded.field("bits"))

    whole = packed.withColumn("path", F.struct("bits", F.col("n_bits").cast("long").alias("n_bits"))).drop("bits", "n_bits")
    return map_column(whole, "path", packed.sparkSession.sparkContext.broadcast(book), unpack_column, "array<int>")


def tune_theta(train: DataFrame, paths: DataFrame, edges: DataFrame, most: int = 8) -> DataFrame:
    """theta, bits_before, bits_after of ``paths`` coded with the dictionary of ``train``, for each length bound.

    Grams are counted once: a shorter bound has the same counts of what it keeps.
    """
    from roadtraj.operators.huffman import codebook
    from roadtraj.operators.twostage import compress_paths
    from roadtraj.plans.scratch import cut

    mined, short, out = cut(mine_grams(train, most, edges)), cut(paths.select("trip_id", "path")), None
    total = short.agg((F.sum(F.size("path")) * 32).alias("bits_before"))
    for theta in range(1, most + 1):
        bits = compress_paths(short, None, codebook(mined.where(F.col("n") <= theta), theta)).agg(F.sum("n_bits").alias("bits_after"))
        row = total.crossJoin(bits).select(F.lit(theta).alias("theta"), "bits_before", "bits_after")
        out = row if out is None else out.unionByName(row)
    return out


def rank_symbols(paths: DataFrame, partitions: int = 8) -> DataFrame:
    """symbol, id, freq: dense ids of string symbols, most frequent first.

    Ranks within range partitions plus the sizes of the partitions before: only
    one number for each partition meets in one task, not the symbols.
    """
    from roadtraj.plans.scratch import cut

    counted = paths.select(F.explode("path").alias("symbol")).groupBy("symbol").agg(F.count(F.lit(1)).alias("freq"))
    placed = cut(counted.repartitionByRange(partitions, F.desc("freq"), "symbol").withColumn("part", F.spark_partition_id()))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    sizes = placed.groupBy("part").count().select("part", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("offset"))
    local = F.row_number().over(Window.partitionBy("part").orderBy(F.desc("freq"), "symbol"))
    return placed.withColumn("local", local).join(sizes, "part").select("symbol", (F.col("local") + F.col("offset")).alias("id"), "freq")
