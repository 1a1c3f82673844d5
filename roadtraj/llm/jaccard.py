"""Exact n-gram Jaccard join as a blocked sparse product of document by n-gram incidence.

Documents are sets of word n-gram hashes; equal sets are one class from the
start. Two size-derived bounds, both exact, keep the product small:

* A document that links with another lacks at most (1 - t) of its grams there.
  Grams with one hash residue are counted over all classes; a class with more
  grams that no other class has than this bound allows can link with nothing.
* Two linked sets differ in at most D grams, D following from their sizes. Dealt
  by hash over more than D segments, they agree in a whole segment, so its digest
  is a signature they share. ``segment_signatures`` deals each set for its own
  size level and for the levels of smaller sets that it may still link with.
  The spare segments make it several that they share, so each set leaves out as many
  but one of its most frequent signatures: of those that two linked sets share, the
  rarest stays in both. What unlinked sets have in common, passages found in many
  documents, goes, and does not tie them to one group that grows with the input.

Sets that share a signature meet in blocks of bounded weight. A block's incidence
matrix is multiplied with its own transpose: overlap counts are accumulated column by
column, and pairs below the bound their sizes set are discarded. This happens
twice. First every set meets the smallest set it shares a signature with, its
centre, and whoever else falls into that block: one copy of a text, whatever the
size of the group. Signatures whose sets hang on one centre by then are done. The
sets of those that are left over, in groups, meet in the blocks of a grid, every
pair of blocks once. Each block returns a star for every connected piece, never all pairs;
components of all stars are found by contraction.

A class is known by 128 bits. Signatures carry 64 of them: that two linked sets
agree in those by chance is the only way to miss a link, and sets that do so by
chance and are no links only meet in a block.

Defined results: a null or blank text is empty and links with nothing; a text
with fewer words than n has its whole sequence as its one gram; rows of one
doc_id are one document each and get the same component when equal; a null
doc_id takes part through equal sets only, and its component is null where no
row with an id has its set; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from math import ceil, exp, sqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from roadtraj.llm.scratch import materialize, release
from roadtraj.llm.textbatch import LOWER, mix64, powers, ragged, slices, text_bytes, word_hashes, words_of

BLOCK_WEIGHT = 150_000  # bytes of text / 6, and 200 for each document
RATIO = 1.3  # sizes of one signature level
_COLUMNS = 2048
_DENSE = 32  # a gram in more rows of a block is a column of a dense product, others are listed
_SEEDS = powers(0x9FB21C651E98DF25, 4096)[0]


def gram_sets(column: pa.Array, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct n-gram hashes, sorted within each document, and each document's bounds."""
    words = words_of(column)
    counts = words.counts()
    hashed = word_hashes(LOWER[words.data], words.start, words.end)
    n_docs = len(counts)
    room = np.repeat(counts, counts) - words.position()
    whole = np.flatnonzero(room >= n)
    gram = np.zeros(len(whole), np.uint64)
    for k in range(n):
        gram = mix64(gram + hashed[whole + k] * _SEEDS[k + 1])
    document = words.document()[whole]
    short = np.flatnonzero((counts > 0) & (counts < n))
    if len(short):
        alone = np.zeros(len(short), np.uint64)
        for k in range(n - 1):
            has = counts[short] > k
            at = np.minimum(words.first[short] + k, len(hashed) - 1)
            alone = np.where(has, mix64(alone + hashed[at] * _SEEDS[k + 1 + n]), alone)
        gram, document = np.concatenate([gram, alone]), np.concatenate([document, short])
    order = np.lexsort((gram, document))
    gram, document = gram[order], document[order]
    fresh = np.ones(len(gram), bool)
    fresh[1:] = (gram[1:] != gram[:-1]) | (document[1:] != document[:-1])
    gram, document = gram[fresh], document[fresh]
    return gram, np.searchsorted(document, np.arange(n_docs + 1))


def set_ids(gram: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """128 bits for each set, two columns; zeros for the empty set."""
    size = np.diff(bounds).astype(np.uint64)
    halves = []
    for seed in (0x5851F42D4C957F2D, 0x14057B7EF767814F):
        sums = np.zeros(len(gram) + 1, np.uint64)
        np.cumsum(mix64(gram ^ np.uint64(seed)), out=sums[1:])
        halves.append(np.where(size > 0, mix64(sums[bounds[1:]] - sums[bounds[:-1]] + size), np.uint64(0)))
    return np.stack(halves, axis=1)


def _id_columns(gram: np.ndarray, bounds: np.ndarray) -> tuple[pa.Array, pa.Array]:
    """set_id (null: empty) and key, the first half of it."""
    ids = set_ids(gram, bounds)
    body = np.ascontiguousarray(ids).tobytes()
    empty = (np.diff(bounds) == 0).tolist()
    return pa.array([None if e else body[16 * k : 16 * k + 16] for k, e in enumerate(empty)], pa.binary()), pa.array(ids[:, 0].view(np.int64))


def _class_rows(batches: Iterator[pa.RecordBatch], n: int) -> Iterator[pa.RecordBatch]:
    for batch in slices(batches):
        gram, bounds = gram_sets(batch.column("text"), n)
        set_id, key = _id_columns(gram, bounds)
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(np.diff(bounds).astype(np.int64)), set_id, key], names=["doc_id", "n_shingles", "set_id", "key"])


def _sampled_rows(batches: Iterator[pa.RecordBatch], n: int, modulus: int) -> Iterator[pa.RecordBatch]:
    for batch in slices(batches):
        gram, bounds = gram_sets(batch.column("text"), n)
        keys = np.repeat(set_ids(gram, bounds)[:, 0], np.diff(bounds))
        at = np.flatnonzero((gram >> np.uint64(7)) % np.uint64(modulus) == 0)
        yield pa.RecordBatch.from_arrays([pa.array(gram[at].view(np.int64)), pa.array(keys[at].view(np.int64))], names=["h", "key"])


def _true_rows(batches: Iterator[pa.RecordBatch], n: int) -> Iterator[pa.RecordBatch]:
    """Rows whose text has the set it is meant to have, not another text of that id."""
    for batch in slices(batches):
        own, _ = _id_columns(*gram_sets(batch.column("text"), n))
        same = [a == b for a, b in zip(own.to_pylist(), batch.column("set_id").to_pylist(), strict=True)]
        yield batch.filter(pa.array(same, pa.bool_()))


def size_levels(most: int, percent: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Smallest size, largest size of a partner, segments and spare segments of each level, for sets of up to ``most`` grams.

    A level is for links whose smaller set has a size in it. With D grams of
    difference at most and D + 1 + spare segments, linked sets agree in more
    segments than are spare. The spare ones outnumber, all but always, those that
    are empty in a set, as an empty segment tells nothing.
    """
    first, widest, segments, spares = [], [], [], []
    low = 1
    while low <= most:
        high = max(low, int(low * RATIO) - 1)
        partner = 100 * high // percent
        apart = (high + partner) * (100 - percent) // (100 + percent)
        spare = 0
        for _ in range(8 * bool(apart)):
            total = apart + 1 + spare
            empty = total * exp(-low / total)
            spare = ceil(empty + 3 * sqrt(empty) + 1)
        first.append(low)
        widest.append(partner)
        segments.append(apart + 1 + spare)
        spares.append(spare)
        low = high + 1
    return tuple(np.array(x, np.int64) for x in (first, widest, segments, spares))


def level_signatures(gram: np.ndarray, bounds: np.ndarray, percent: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Signatures of all sets, the row and the level of each, and how many of its level the row may leave out.

    Linked sets that are not equal share more than that in one level. A set with more
    empty segments than are spare also signs those, so that the rest of the links,
    between two such sets, is not lost, and leaves out nothing.
    """
    size = np.diff(bounds)
    first, widest, segments, spares = size_levels(int(size.max(initial=0)), percent)
    out, rows, levels, surplus = [], [], [], []
    level = np.searchsorted(first, size, side="right") - 1
    while True:
        at = np.flatnonzero((level >= 0) & (size > 0))
        at = at[size[at] <= widest[level[at]]] if len(at) else at
        if not len(at):
            break
        wide = segments[level[at]]
        offset = np.concatenate([[0], np.cumsum(wide)])
        take = ragged(bounds[:-1][at], size[at])
        own = np.repeat(np.arange(len(at)), size[at])
        picked = gram[take]
        cell = offset[own] + ((picked >> np.uint64(11)) % wide[own].astype(np.uint64)).astype(np.int64)
        sums = np.zeros(offset[-1], np.uint64)
        np.add.at(sums, cell, mix64(picked ^ np.uint64(0x2545F4914F6CDD1D)))
        filled = np.zeros(offset[-1], bool)
        filled[cell] = True
        row = np.repeat(np.arange(len(at)), wide)
        spare = spares[level[at]] - np.bincount(row[~filled], minlength=len(at))
        signs = filled | (spare < 0)[row]
        place = np.arange(offset[-1]) - offset[row]
        label = (place + (level[at][row] << 40)).astype(np.uint64)
        out.append(mix64(sums ^ mix64(label + np.uint64(1)))[signs])
        rows.append(at[row[signs]])
        levels.append(level[at][row[signs]])
        surplus.append(np.maximum(spare, 0)[row[signs]])
        level = level - 1
    if not out:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    return tuple(np.concatenate(x) for x in (out, rows, levels, surplus))


def segment_signatures(gram: np.ndarray, bounds: np.ndarray, percent: int) -> tuple[np.ndarray, np.ndarray]:
    """Signatures of all sets, and the row of each. Linked sets that are not equal share at least one."""
    return level_signatures(gram, bounds, percent)[:2]


def _signature_rows(batches: Iterator[pa.RecordBatch], n: int, percent: int) -> Iterator[pa.RecordBatch]:
    for batch in slices(batches):
        h, row, level, surplus = level_signatures(*gram_sets(batch.column("text"), n), percent)
        columns = [pa.array(h.view(np.int64)), batch.column("key").take(pa.array(row)), pa.array(level.astype(np.int32)), pa.array(surplus.astype(np.int32))]
        yield pa.RecordBatch.from_arrays(columns, names=["h", "key", "level", "surplus"])


def overlaps(gram: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Overlap counts of all pairs of rows: the incidence matrix times its transpose, column by column."""
    n = len(bounds) - 1
    columns, code = np.unique(gram, return_inverse=True)
    times = np.bincount(code, minlength=len(columns))
    row = np.repeat(np.arange(n), np.diff(bounds))
    order = np.argsort(code, kind="stable")
    row, code = row[order], code[order]
    shared = np.zeros((n, n), np.int64)
    sparse = np.flatnonzero((times[code] > 1) & (times[code] <= _DENSE))
    thin_row, thin = row[sparse], code[sparse]
    cells = []
    for step in range(1, _DENSE):
        at = np.flatnonzero(thin[step:] == thin[:-step])
        if not len(at):
            break
        cells.append(thin_row[at] * n + thin_row[at + step])
    if cells:
        shared += np.bincount(np.concatenate(cells), minlength=n * n).reshape(n, n)
    dense = np.flatnonzero(times[code] > _DENSE)
    thick_row, thick = row[dense], np.unique(code[dense], return_inverse=True)[1]
    for lo in range(0, int(thick.max(initial=-1)) + 1, _COLUMNS):
        i, j = np.searchsorted(thick, [lo, lo + _COLUMNS])
        part = np.zeros((n, _COLUMNS), np.float32)
        part[thick_row[i:j], thick[i:j] - lo] = 1
        shared += np.triu(part @ part.T, 1).astype(np.int64)
    return shared


def _pieces(linked: np.ndarray) -> np.ndarray:
    """Smallest member of each row's connected piece of a symmetric boolean matrix."""
    label = np.arange(len(linked))
    near = [np.flatnonzero(x) for x in linked]
    while True:
        lower = label.copy()
        for i, at in enumerate(near):
            if len(at):
                lower[i] = min(lower[i], label[at].min())
        lower = lower[lower]
        if (lower == label).all():
            return label
        label = lower


def block_links(gram: np.ndarray, bounds: np.ndarray, percent: int) -> np.ndarray:
    """Smallest member of each row's piece of the link graph of a block."""
    shared, size = overlaps(gram, bounds), np.diff(bounds)
    low, high = np.nonzero(shared)
    met = shared[low, high]
    linked = 100 * met >= percent * (size[low] + size[high] - met)
    graph = np.zeros(shared.shape, bool)
    graph[low[linked], high[linked]] = graph[high[linked], low[linked]] = True
    return _pieces(graph)


_STARS = pa.schema([("a", pa.binary()), ("b", pa.binary())])


def _block_rows(batches: Iterator[pa.RecordBatch], n: int, percent: int, most: int) -> Iterator[pa.RecordBatch]:
    """Stars of the blocks of rows that come ordered by block; whole small blocks share a product."""
    held: list[pa.RecordBatch] = []

    def product():
        table = pa.Table.from_batches(held).combine_chunks()
        label = block_links(*gram_sets(table.column("text").combine_chunks(), n), percent)
        at = np.flatnonzero(label != np.arange(len(label)))
        ids = table.column("set_id").combine_chunks()
        return pa.RecordBatch.from_arrays([ids.take(pa.array(at)), ids.take(pa.array(label[at]))], schema=_STARS)

    weight, last = 0, None
    for batch in slices(batches, most=3 * most):
        keys = list(zip(*(batch.column(c).to_pylist() for c in ("part", "i", "j")), strict=True))
        sizes = np.diff(text_bytes(batch.column("text"))[1]) // 6 + 200
        lo = 0
        for k, key in enumerate(keys):
            if key != last and weight >= most:
                if k > lo:
                    held.append(batch.slice(lo, k - lo))
                yield product()
                held.clear()
                lo, weight = k, 0
            last, weight = key, weight + int(sizes[k])
        held.append(batch.slice(lo))
    if held:
        yield product()


def multiply(dealt: DataFrame, n: int, percent: int) -> DataFrame:
    """a, b: stars of the pieces found in the blocks (part, i, j) of rows with set_id and text; ``rank`` false comes first and is a star's centre."""
    most = BLOCK_WEIGHT
    ordered = dealt.select("part", "i", "j", "rank", "set_id", "text").repartition("part", "i", "j").sortWithinPartitions("part", "i", "j", "rank")
    return ordered.mapInArrow(lambda batches: _block_rows(batches, n, percent, most), "a binary, b binary")


def components(edges: DataFrame, tag: str) -> DataFrame:
    """node, label (one node of its component) of the nodes of undirected edges a, b.

    In each round every node moves onto its smallest neighbour or stays, and only
    edges between different places go on, so rounds get smaller; the places of all
    rounds, one after the other, lead to the label.
    """
    left = materialize(edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a <> b").distinct(), f"{tag}-edges")
    moves = []
    for round_ in range(64):
        both = left.union(left.select("b", "a")).groupBy(F.col("a").alias("node")).agg(F.min("b").alias("m"))
        move = materialize(both.select("node", F.least("node", "m").alias("to")), f"{tag}-{round_}")
        moves.append(move)
        ends = [move.select(F.col("node").alias(c), F.col("to").alias(f"_{c}")) for c in "ab"]
        moved = left.join(ends[0], "a").join(ends[1], "b").where("_a <> _b").select(F.least("_a", "_b").alias("a"), F.greatest("_a", "_b").alias("b")).distinct()
        was, left = left, materialize(moved, f"{tag}-left")
        release(was)
        if left.isEmpty():
            break
    else:
        raise RuntimeError("components did not settle")
    labels = moves[-1].select("node", F.col("to").alias("label"))
    for move in reversed(moves[:-1]):
        onward = labels.withColumnRenamed("node", "to")
        labels = move.join(onward, "to", "left").select("node", F.coalesce("label", "to").alias("label"))
    return labels


def _blocks(member: DataFrame) -> DataFrame:
    """part, blocks: how many blocks of bounded weight the sets (part, weight) of a part fill."""
    return member.groupBy("part").agg(F.greatest(F.lit(1), F.ceil(F.sum("weight") / F.lit(BLOCK_WEIGHT))).cast("int").alias("blocks"))


def _with_text(placed: DataFrame, texts: DataFrame) -> DataFrame:
    """The blocks' rows with their texts; a join by sort at any size, as the texts grow with the input."""
    return texts.select("key", "set_id", "text").hint("merge").join(placed, "key")


def rarest(signed: DataFrame) -> DataFrame:
    """h, key: the signatures (h, key, level, surplus) of more than one set, without the most frequent ones of each set and level, as many as are surplus."""
    common = signed.groupBy("h").agg(F.min("key").alias("lo"), F.max("key").alias("hi"), F.count(F.lit(1)).alias("times")).where("lo < hi").select("h", "times")
    common = materialize(common, "common")
    by = Window.partitionBy("key", "level").orderBy(F.desc("times"), F.desc("h"))
    # Sets that agree in the key by chance leave out no more together than the one that may leave out less.
    fewest = F.min("surplus").over(Window.partitionBy("key", "level"))
    ranked = signed.hint("merge").join(common, "h").withColumns({"_n": F.row_number().over(by), "_surplus": fewest})
    return ranked.where("_n > _surplus").select("h", "key")


def linked_classes(docs: DataFrame, n: int, percent: int) -> tuple[DataFrame, DataFrame]:
    """(doc_id, n_shingles, set_id, key) of all rows, and (node, label) of classes that link with another."""
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    classes = materialize(keyed.mapInArrow(lambda batches: _class_rows(batches, n), "doc_id long, n_shingles long, set_id binary, key long"), "classes")
    modulus = -(-45 // (100 - percent)) if percent < 100 else 5
    sampled = keyed.select("text").mapInArrow(lambda batches: _sampled_rows(batches, n, modulus), "h long, key long")
    lone = sampled.groupBy("h").agg(F.min("key").alias("lo"), F.max("key").alias("hi")).where("lo = hi").groupBy("lo").agg(F.count(F.lit(1)).alias("lone"))
    heads = classes.where("set_id IS NOT NULL").groupBy("set_id").agg(F.first("key").alias("key"), F.first("n_shingles").alias("size"), F.min("doc_id").alias("head"))
    # Sets that agree in the key by chance share their lone grams' count, so the bound does not judge them.
    alone = F.col("_sets") == 1
    judged = heads.hint("merge").join(lone, heads["key"] == lone["lo"], "left").withColumn("_sets", F.count(F.lit(1)).over(Window.partitionBy("key")))
    near = judged.where((100 * F.coalesce("lone", F.lit(0)) <= (100 - percent) * F.col("size")) | ~alone)
    near = materialize(near.where("head IS NOT NULL").select("set_id", "key", "head"), "near")

    texts = keyed.hint("merge").join(near, keyed["doc_id"] == near["head"]).select("set_id", "key", "text")
    texts = texts.mapInArrow(lambda batches: _true_rows(batches, n), "set_id binary, key long, text string")
    texts = materialize(texts, "texts")  # a repeated row's text stands twice; it links with itself only
    weights = texts.select("key", "set_id", (F.octet_length("text") / F.lit(6) + 200).alias("weight"))

    signed = texts.mapInArrow(lambda batches: _signature_rows(batches, n, percent), "h long, key long, level int, surplus int")
    kept = materialize(rarest(signed), "kept")
    shared = kept.groupBy("h").agg(F.min("key").alias("lo"), F.max("key").alias("hi")).where("lo < hi").select("h", "lo")
    shared = materialize(shared, "shared")
    met = materialize(kept.hint("merge").join(shared, "h").select("h", "key", "lo"), "met")
    release(near, kept, shared)

    # Every set with the smallest one that it shares a signature with.
    stars = materialize(met.groupBy("key").agg(F.min("lo").alias("part")), "stars")
    blocks = _blocks(weights.join(stars, "key"))
    spread = F.pmod(F.xxhash64("key"), F.col("blocks")).cast("int")
    own = stars.where("key <> part").join(blocks, "part").select("key", "part", spread.alias("i"))
    centres = blocks.select(F.col("part").alias("key"), "part", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("i"))
    first = own.unionByName(centres).withColumn("j", F.col("i")).withColumn("rank", F.col("key") != F.col("part"))
    first = materialize(multiply(_with_text(first, texts), n, percent), "first")

    # Signatures whose sets do not hang on one centre yet: their sets, grouped, in a grid of blocks.
    hangs = first.groupBy("a").agg(F.min("b").alias("b"))
    hangs = hangs.join(hangs.select(F.col("a").alias("b"), F.col("b").alias("c")), "b", "left").select(F.col("a").alias("_set"), F.coalesce("c", "b").alias("centre"))
    label = F.xxhash64(F.coalesce("centre", "set_id")).alias("l")
    of_key = materialize(weights.join(hangs, weights["set_id"] == hangs["_set"], "left").select("key", "weight", label), "labels")
    with_label = met.select("h", "key").hint("merge").join(of_key.select("key", "l"), "key")
    open_ = with_label.groupBy("h").agg(F.min("l").alias("lo"), F.max("l").alias("hi")).where("lo < hi").select("h", "lo")
    open_ = materialize(open_, "open")
    left_over = materialize(with_label.hint("merge").join(open_, "h").select("key", "l", "lo").distinct(), "left")
    release(met, stars, open_)
    groups = components(left_over.select(F.col("l").alias("a"), F.col("lo").alias("b")).distinct(), "groups")
    member = left_over.select("key", "l").distinct().join(groups, F.col("l") == groups["node"]).select("key", F.col("label").alias("part"))
    member = materialize(member.join(of_key.select("key", "weight"), "key"), "member")
    placed = member.join(_blocks(member), "part").select("key", "part", "blocks", spread.alias("own"))
    grid = placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    grid = grid.select("key", "part", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), F.lit(True).alias("rank"))
    second = multiply(_with_text(grid, texts), n, percent)
    labels = components(first.unionByName(second), "links")
    release(texts, first, of_key, left_over, member)
    return classes, labels


def join_components(docs: DataFrame, n: int = 5, percent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id of each document row."""
    classes, labels = linked_classes(docs, n, percent)
    heads = classes.where("set_id IS NOT NULL").groupBy("set_id").agg(F.min("doc_id").alias("head"))
    tops = heads.join(labels, heads["set_id"] == labels["node"], "left").select("set_id", "head", F.coalesce("label", "set_id").alias("label"))
    least = tops.groupBy("label").agg(F.min("head").alias("component_id"))
    of_set = materialize(tops.join(least, "label").select(F.col("set_id").alias("_set"), "component_id"), "components")
    joined = classes.join(of_set, classes["set_id"] == of_set["_set"], "left")
    return joined.select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))


def keep_one(docs: DataFrame, n: int = 5, percent: int = 80) -> DataFrame:
    """One document of each component, that of the smallest id. Documents without words and rows without an id all stay."""
    names = docs.columns
    found = join_components(docs, n, percent).where("doc_id IS NOT NULL").groupBy("doc_id").agg(F.min("component_id").alias("_component"), F.max("n_shingles").alias("_grams")).withColumnRenamed("doc_id", "_id")
    keyed = docs.where(F.col("doc_id").isNotNull()).withColumn("_doc", F.col("doc_id").cast("long"))
    heads = keyed.join(found, keyed["_doc"] == found["_id"]).where("_component = _doc")
    first = heads.withColumn("_n", F.row_number().over(Window.partitionBy("_doc").orderBy("text"))).where("_n = 1 OR _grams = 0")
    return first.select(*[keyed[c] for c in names]).unionByName(docs.where(F.col("doc_id").isNull()))
