"""Suffix-array removal of repeated byte strings.

A string of ``length`` bytes that starts at two places is a repeat, in one text
or in two. Finding them takes three steps.

1. Anchors. In every window of GRAM-byte strings that fits into ``length`` bytes
   the one with the smallest hash (the first of equals) is an anchor. Equal
   strings have equal anchors at equal offsets, so an anchor hash that occurs
   once proves that no string around it repeats. One anchor stands per
   (length - GRAM) / 2 bytes or so.
2. Contexts. The bytes within reach of an anchor that occurs elsewhere are its
   context: every string that has this anchor lies in it, at one offset. Equal
   contexts of one anchor are counted, not gathered. A context that occurs twice
   repeats throughout. Where an anchor has several different contexts, these are
   compared by a suffix array.
3. Suffix arrays. The contexts of one anchor are aligned at it. A byte with its
   place is a symbol, symbols of later places being greater, and a context's end
   is smallest. The array of that text is built by linear grouping: suffixes that
   share their longest Lyndon prefix form groups, these are processed from the
   largest down, and each moves the previous smaller suffixes of its members up
   in their own groups. Here a longest Lyndon prefix runs to the context's end and
   the previous smaller suffix stands one place before, so all groups of a place are
   processed at once, by one counting pass over the place before it, and what
   a pass leaves is the order to emit: no renaming and no recursion
   (``place_orders``; ``suffix_array`` is the same construction for any text).
   Common prefixes of neighbours come along, so strings that stand together in the
   order over ``length`` bytes are the repeats, byte for byte.

Anchors with very many different contexts, where one task would gather too much,
have their strings counted by hash instead, which is exact at any size.

Defined results: a null text is empty; a null doc_id is a document like others;
repeated rows repeat each other; other columns are ignored; an empty table gives
an empty table.
"""

from __future__ import annotations

import hashlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from roadtraj.llm.scratch import materialize
from roadtraj.llm.textbatch import BYTE_VALUES, mix64, powers, ragged, run_hashes, slices, text_bytes

LENGTH = 200
GRAM = 16
MANY = 20_000  # of one anchor: what a task may gather, some 10 MB of contexts
CONTEXTS = 8192  # contexts of whole anchors in one array
REACH = LENGTH - GRAM
_BASE = 0xC2B2AE3D27D4EB4F


def suffix_array(text: list[int]) -> list[int]:
    """Start places of all suffixes in ascending order, by linear grouping; the empty suffix is first."""
    n = len(text) + 1
    symbols = [*text, min(text, default=1) - 1]
    order = sorted(range(n), key=symbols.__getitem__)
    place, group, size = [0] * n, [0] * n, [0] * (n + 1)
    now = 0
    for at, i in enumerate(order):
        place[i] = at
        if symbols[i] != symbols[order[now]]:
            now = at
        group[i] = now
        size[now] += 1
    smaller = [-1] * n  # nearest earlier suffix of a lower group
    high = n
    while high > 1:
        low = group[order[high - 1]]
        members = sorted(order[low:high])
        times: dict[int, int] = {}
        for i in members:
            j = i - 1
            while j >= 0 and group[j] >= low:
                j = smaller[j]
            smaller[i] = j
            if j >= 0:
                times[j] = times.get(j, 0) + 1
        # Whoever precedes this group grows by its prefix: up, out of its group, the more often the higher.
        levels: dict[int, list[int]] = {}
        for j, k in times.items():
            levels.setdefault(k, []).append(j)
        for k in sorted(levels, reverse=True):
            moved = levels[k]
            for j in moved:
                g = group[j]
                last = g + size[g] - 1
                other, here = order[last], place[j]
                order[here], order[last] = other, j
                place[other], place[j] = here, last
                size[g] -= 1
            for j in moved:
                g = group[j]
                group[j] = g + size[g]
            for j in moved:
                size[group[j]] += 1
        high = low
    # From the smallest up: a suffix places those whose next smaller suffix it is, each at the front of its group.
    free = list(range(n))
    out = [0] * n
    out[0] = n - 1
    for r in range(n):
        j = out[r]
        stop, i = smaller[j], j - 1
        while i != stop:
            g = group[i]
            out[free[g]] = i
            free[g] += 1
            i = smaller[i]
    return out


def common_prefixes(text: list[int], order: list[int]) -> list[int]:
    """Length of the common prefix of each suffix in ``order`` with the one before it."""
    n = len(text)
    rank = [0] * (n + 1)
    for r, i in enumerate(order):
        rank[i] = r
    out, h = [0] * (n + 1), 0
    for i in range(n):
        j = order[rank[i] - 1]
        while i + h < n and j + h < n and text[i + h] == text[j + h]:
            h += 1
        out[rank[i]] = h
        if h:
            h -= 1
    return out


def _key(docs: DataFrame) -> DataFrame:
    """doc_id, k and tie (96 bits that tell rows apart, but for rows alike in id and text), text."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("doc_id", "text").alias("k"), F.hash("text").alias("tie"), F.coalesce("text", F.lit("")).alias("text"))


def _gram_hashes(data: np.ndarray, length: int, base: int = _BASE) -> np.ndarray:
    """Hash of the ``length`` bytes at each place that has them."""
    out, step = [], 1 << 18
    for lo in range(0, len(data) - length + 1, step):
        part = data[lo : lo + step + length - 1]
        out.append(run_hashes(BYTE_VALUES[part], np.arange(len(part) - length + 1), length, base))
    return np.concatenate(out) if out else np.zeros(0, np.uint64)


def anchor_places(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of anchors in the bytes of a batch, and their hashes."""
    width = LENGTH - GRAM + 1
    grams = _gram_hashes(data, GRAM)
    if not len(grams):
        return np.zeros(0, np.int64), grams
    key = (grams & np.uint64(0xFFFFFFFF00000000)) | np.arange(len(grams), dtype=np.uint64)
    rows = -(-len(key) // width) + 1
    padded = np.full(rows * width, np.iinfo(np.uint64).max)
    padded[: len(key)] = key
    blocks = padded.reshape(rows, width)
    ahead = np.minimum.accumulate(blocks, axis=1).ravel()
    behind = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    starts = ragged(offsets[:-1], np.maximum(np.diff(offsets) - LENGTH + 1, 0))
    best = np.minimum(behind[starts], ahead[starts + width - 1]) & np.uint64(0xFFFFFFFF)
    change = np.ones(len(best), bool)
    change[1:] = best[1:] != best[:-1]
    places = np.unique(best[change].astype(np.int64))
    return places, grams[places]


def _extent(places: np.ndarray, document: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return np.maximum(places - REACH, offsets[document]), np.minimum(places + LENGTH, offsets[document + 1])


def _anchor_rows(batches: Iterator[pa.RecordBatch], with_context: bool) -> Iterator[pa.RecordBatch]:
    for batch in slices(batches, most=1 << 20):
        data, offsets = text_bytes(batch.column("text"))
        places, hashes = anchor_places(data, offsets)
        document = np.searchsorted(offsets, places, side="right") - 1
        if with_context:
            lo, hi = _extent(places, document, offsets)
            body = data.tobytes()
            context = [xxhash.xxh3_64_intdigest(body[a:b], p - a) for a, b, p in zip(lo.tolist(), hi.tolist(), places.tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(hashes.view(np.int64)), pa.array(np.array(context, np.uint64).view(np.int64))], names=["h", "context"])
        else:
            rows = pa.array(document)
            yield pa.RecordBatch.from_arrays([pa.array(hashes.view(np.int64)), batch.column("k").take(rows), batch.column("tie").take(rows), pa.array((places - offsets[document]).astype(np.int32))], names=["h", "k", "tie", "pos"])


def _digest_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in slices(batches):
        data, offsets = text_bytes(batch.column("text"))
        body = memoryview(data)
        unmarked = batch.column("marks").is_null().to_numpy(zero_copy_only=False)
        digests = pa.array([hashlib.sha256(body[a:b]).hexdigest() for a, b in zip(offsets[:-1], offsets[1:], strict=True)], pa.string())
        text = batch.column("text").take(pa.array(np.arange(batch.num_rows), mask=unmarked))
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("k"), batch.column("tie"), pa.array(np.diff(offsets)), digests, text, batch.column("marks")], names=["doc_id", "k", "tie", "n_bytes", "digest", "text", "marks"])


WHOLE, MIXED, HOT = 0, 1, 2


def _marks(batch: pa.RecordBatch, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Places, kinds and documents of a batch's marked anchors."""
    marks = batch.column("marks")
    per = np.diff(np.asarray(marks.offsets))
    flat = marks.flatten()
    document = np.repeat(np.arange(batch.num_rows), per)
    return flat.field("pos").to_numpy() + offsets[document], flat.field("kind").to_numpy(), document


def _context_rows(batches: Iterator[pa.RecordBatch], with_bytes: bool) -> Iterator[pa.RecordBatch]:
    """Contexts of mixed anchors: with their bytes, equal ones of a batch counted; or with their places."""
    for batch in slices(batches):
        data, offsets = text_bytes(batch.column("text"))
        places, kinds, document = _marks(batch, offsets)
        at = kinds == MIXED
        places, document = places[at], document[at]
        if not len(places):
            continue
        lo, hi = _extent(places, document, offsets)
        hashes = _hashes_at(data, places)
        body = data.tobytes()
        ids = [xxhash.xxh3_128_digest(body[a:b], p - a) for a, b, p in zip(lo.tolist(), hi.tolist(), places.tolist(), strict=True)]
        if with_bytes:
            count, first = Counter(zip(hashes.tolist(), ids, strict=True)), {}
            for n, key in enumerate(zip(hashes.tolist(), ids, strict=True)):
                first.setdefault(key, n)
            pick = list(first.values())
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(hashes[pick].view(np.int64)), pa.array([ids[n] for n in pick], pa.binary()), pa.array((places - lo)[pick].astype(np.int32)),
                    pa.array([body[lo[n] : hi[n]] for n in pick], pa.binary()), pa.array([count[k] for k in first], pa.int64()),
                ],
                names=["h", "context", "before", "body", "times"],
            )
        else:
            rows = pa.array(document)
            yield pa.RecordBatch.from_arrays([pa.array(hashes.view(np.int64)), pa.array(ids, pa.binary()), batch.column("k").take(rows), batch.column("tie").take(rows), pa.array((places - offsets[document]).astype(np.int32))], names=["h", "context", "k", "tie", "pos"])


def _hashes_at(data: np.ndarray, places: np.ndarray) -> np.ndarray:
    """Gram hashes at some places, the same values as everywhere."""
    up, _ = powers(_BASE, GRAM)
    return mix64((BYTE_VALUES[data[places[:, None] + np.arange(GRAM)]] * up).sum(axis=1, dtype=np.uint64))


def _least(values: np.ndarray, first: np.ndarray, last: np.ndarray) -> np.ndarray:
    """Minimum of values[first..last], ends included, for many ranges."""
    power = np.frexp((last - first + 1).astype(np.float64))[1] - 1  # of two, at most the range's width
    out = np.empty(len(first), values.dtype)
    table = values
    for k in range(int(power.max(initial=-1)) + 1):
        at = np.flatnonzero(power == k)
        if len(at):
            out[at] = np.minimum(table[first[at]], table[last[at] - (1 << k) + 1])
        if len(table) > 1 << k:
            table = np.minimum(table[: -(1 << k)], table[1 << k :])
    return out


def place_orders(columns: np.ndarray, most: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """Place, order of the rows' suffixes from there, common prefix of each with the one before (``most`` at most).

    ``columns`` is the matrix of rows by places, transposed. Places come from the last down.
    """
    rows = columns.shape[1]
    order, common = np.arange(rows), np.zeros(rows, np.int16)
    for place in range(len(columns) - 1, -1, -1):
        symbol = columns[place][order]
        moved = np.argsort(symbol, kind="stable")  # a counting sort: symbols are bytes
        symbol = symbol[moved]
        same = np.flatnonzero(symbol[1:] == symbol[:-1])
        after = np.zeros(rows, np.int16)
        after[same + 1] = np.minimum(_least(common, moved[same] + 1, moved[same + 1]) + 1, most)
        order, common = order[moved], after
        yield place, order, common


def repeated_strings(matrix: np.ndarray, lo: np.ndarray, hi: np.ndarray, times: np.ndarray) -> np.ndarray:
    """Which strings (context x start) occur twice. Contexts fill lo to hi of their rows and are aligned at the anchor."""
    starts = matrix.shape[1] - LENGTH + 1
    found = np.zeros((len(matrix), starts), bool)
    for place, order, common in place_orders(np.ascontiguousarray(matrix.T), LENGTH):
        if place < starts:
            run = np.cumsum(common < LENGTH) - 1
            fits = ((lo <= place) & (place + LENGTH <= hi))[order]
            occurs = np.bincount(run, weights=np.where(fits, times[order], 0))
            found[order, place] = fits & (occurs[run] > 1)
    return found


_CUTS = pa.schema([("h", pa.int64()), ("context", pa.binary()), ("cuts", pa.list_(pa.int32()))])


def _resolve(rows: pa.Table) -> pa.RecordBatch:
    """Cuts of the distinct contexts of whole anchors, in order; rows of one context stand together."""
    rows = rows.combine_chunks()
    h, context = rows.column("h").to_numpy(), rows.column("context").combine_chunks()
    marks = np.frombuffer(b"".join(context.to_pylist()), np.uint64).reshape(-1, 2)
    fresh = np.ones(len(h), bool)
    fresh[1:] = (h[1:] != h[:-1]) | (marks[1:] != marks[:-1]).any(1)
    first = np.flatnonzero(fresh)
    times = np.add.reduceat(rows.column("times").to_numpy(), first)
    body = rows.column("body").combine_chunks().take(pa.array(first))
    data, bounds = text_bytes(body)
    lo = REACH - rows.column("before").to_numpy()[first].astype(np.int64)
    size = np.diff(bounds)
    width = REACH + LENGTH
    matrix = np.zeros((len(first), width), np.uint8)
    matrix.ravel()[ragged(np.arange(len(first)) * width + lo, size)] = data
    step = np.diff(np.pad(repeated_strings(matrix, lo, lo + size, times), ((0, 0), (1, 1))).astype(np.int8), axis=1)
    (row, start), (_, stop) = np.nonzero(step == 1), np.nonzero(step == -1)
    per = np.bincount(row, minlength=len(first))
    cut = np.flatnonzero(per)
    flat = np.stack([start - REACH, stop - 1 + LENGTH - REACH], axis=1).ravel().astype(np.int32)
    offsets = np.concatenate([[0], np.cumsum(2 * per[cut])]).astype(np.int32)
    at = pa.array(first[cut])
    return pa.RecordBatch.from_arrays([pa.array(h[first[cut]]), context.take(at), pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat))], schema=_CUTS)


def _resolve_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Cuts of each distinct context; rows come ordered by anchor and context, and an anchor's rows are taken together."""
    held, count = [], 0
    for batch in batches:
        held.append(batch)
        count += batch.num_rows
        if count >= CONTEXTS:
            rows = pa.Table.from_batches(held)
            h = rows.column("h").to_numpy()
            whole = int(np.flatnonzero(h != h[-1])[-1]) + 1 if h[0] != h[-1] else 0
            if whole:
                yield _resolve(rows.slice(0, whole))
            held = rows.slice(whole).to_batches()
            count -= whole
    if count:
        yield _resolve(pa.Table.from_batches(held))


def _string_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Every string around hot anchors, hashed in 128 bits."""
    for batch in slices(batches, most=1 << 18):  # each byte begins a string, which takes some hundred bytes here
        data, offsets = text_bytes(batch.column("text"))
        places, kinds, document = _marks(batch, offsets)
        at = kinds == HOT
        if not at.any():
            continue
        lo, hi = _extent(places[at], document[at], offsets)
        starts = np.unique(ragged(lo, hi - lo - LENGTH + 1))
        of = np.searchsorted(offsets, starts, side="right") - 1
        rows = pa.array(of)
        one, two = _gram_hashes(data, LENGTH), _gram_hashes(data, LENGTH, 0xA0761D6478BD642F)
        yield pa.RecordBatch.from_arrays([pa.array(one[starts].view(np.int64)), pa.array(two[starts].view(np.int64)), batch.column("k").take(rows), batch.column("tie").take(rows), pa.array((starts - offsets[of]).astype(np.int32))], names=["h1", "h2", "k", "tie", "pos"])


def _removal_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in slices(batches):
        data, offsets = text_bytes(batch.column("text"))
        change = np.zeros(len(data) + 1, np.int64)
        places, kinds, document = _marks(batch, offsets)
        lo, hi = _extent(places[kinds == WHOLE], document[kinds == WHOLE], offsets)
        np.add.at(change, lo, 1)
        np.add.at(change, hi, -1)
        cuts = batch.column("cuts")
        per = np.diff(np.asarray(cuts.offsets))
        flat = cuts.flatten().to_numpy() + np.repeat(offsets[:-1], per)
        np.add.at(change, flat[0::2], 1)
        np.add.at(change, flat[1::2], -1)
        gone = np.cumsum(change)[:-1] > 0
        first = gone.copy()
        first[1:] &= ~gone[:-1]
        edges = offsets[:-1][offsets[:-1] < len(data)]
        first[edges] = gone[edges]
        sums, runs = np.concatenate([[0], np.cumsum(gone)]), np.concatenate([[0], np.cumsum(first)])
        kept = memoryview(np.ascontiguousarray(data[~gone]))
        bounds = offsets - sums[offsets]
        digests = pa.array([hashlib.sha256(kept[a:b]).hexdigest() for a, b in zip(bounds[:-1], bounds[1:], strict=True)], pa.string())
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(np.diff(offsets)), pa.array(np.diff(sums[offsets])), pa.array(np.diff(runs[offsets])), digests, pa.array([bytes(kept[a:b]) for a, b in zip(bounds[:-1], bounds[1:], strict=True)], pa.binary())], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])


def remove_repeats(docs: DataFrame, with_bytes: bool = False) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 (and the kept bytes) per document row."""
    keyed = _key(docs)
    seen = keyed.select("text").mapInArrow(lambda batches: _anchor_rows(batches, True), "h long, context long")
    many = seen.groupBy("h").agg(F.count(F.lit(1)).alias("n"), F.min("context").alias("lo"), F.max("context").alias("hi")).where("n > 1")
    kind = F.when(F.col("lo") == F.col("hi"), WHOLE).when(F.col("n") > MANY, HOT).otherwise(MIXED)
    shared = materialize(many.select("h", kind.alias("kind")), "anchors")
    found = keyed.mapInArrow(lambda batches: _anchor_rows(batches, False), "h long, k long, tie int, pos int")
    marks = found.join(shared, "h").groupBy("k", "tie").agg(F.collect_set(F.struct("pos", "kind")).alias("marks"))
    joined = _beside(keyed, marks, "marks")
    looked = materialize(joined.mapInArrow(_digest_rows, "doc_id long, k long, tie int, n_bytes long, digest string, text string, marks array<struct<pos: int, kind: int>>"), "digests")
    near = looked.where(F.col("text").isNotNull()).select("doc_id", "k", "tie", "text", "marks", "n_bytes", "digest")

    contexts = near.select("k", "tie", "text", "marks").where(F.expr(f"exists(marks, m -> m.kind = {MIXED})"))
    bodies = contexts.mapInArrow(lambda batches: _context_rows(batches, True), "h long, context binary, before int, body binary, times long")
    cuts = materialize(bodies.repartition("h").sortWithinPartitions("h", "context").mapInArrow(_resolve_rows, "h long, context binary, cuts array<int>"), "cuts")
    where = contexts.mapInArrow(lambda batches: _context_rows(batches, False), "h long, context binary, k long, tie int, pos int")
    mixed = where.join(cuts, ["h", "context"]).select("k", "tie", F.expr("transform(cuts, c -> c + pos)").alias("cuts"))

    hot = near.select("k", "tie", "text", "marks").where(F.expr(f"exists(marks, m -> m.kind = {HOT})"))
    strings = hot.mapInArrow(_string_rows, "h1 long, h2 long, k long, tie int, pos int")
    again = materialize(strings.groupBy("h1", "h2").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("h1", "h2"), "strings")
    hits = strings.join(again, ["h1", "h2"]).select("k", "tie", F.array(F.col("pos"), F.col("pos") + LENGTH).alias("cuts"))
    per = mixed.unionByName(hits).groupBy("k", "tie").agg(F.flatten(F.collect_set("cuts")).alias("cuts"))
    ready = _beside(near, per, "cuts").withColumn("cuts", F.coalesce("cuts", F.expr("cast(array() as array<int>)")))
    cut = ready.select("doc_id", "text", "marks", "cuts").mapInArrow(_removal_rows, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary")
    names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"] + ["kept"] * with_bytes
    zero = F.lit(0).cast("long")
    whole = looked.where(F.col("text").isNull()).select("doc_id", "n_bytes", zero.alias("n_removed"), zero.alias("n_spans"), F.col("digest").alias("kept_sha256"), F.lit(None).cast("binary").alias("kept"))
    return cut.select(*names).unionByName(whole.select(*names))


def _beside(left: DataFrame, right: DataFrame, column: str) -> DataFrame:
    """``left`` with ``column`` of the row of ``right`` that has its key."""
    other = right.select(F.col("k").alias("_k"), F.col("tie").alias("_tie"), column)
    return left.join(other, (left["k"] == other["_k"]) & (left["tie"] == other["_tie"]), "left").drop("_k", "_tie")
