"""Substring removal over words, with difference-cover anchors.

A repeat is a window of ``window`` consecutive words of one document whose word
sequence also starts in a document of smaller id. Only positions whose index
modulo the period lies in a difference cover are hashed at first (``anchors``).
For two equal windows at i and j some shift below the period puts both i + shift
and j + shift on cover positions, so both windows hold one anchor with the same
hash. Anchors that meet another document mark where a window may repeat; there,
and only there, whole windows are hashed in 96 bits and compared by value.

Shuffles carry hashes and positions; texts are shuffled once, and those of
marked documents once more. Groups are reduced to the smallest id before they
are shuffled and the joins back are plain, so a hash that a third of all rows
share is split.

Defined results: a null text has no words; a null doc_id is never a smaller id
and loses nothing; rows of one id do not remove each other, whether repeated
rows or not; windows are judged on the input; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from roadtraj.llm.scratch import materialize, release
from roadtraj.llm.textbatch import joined_words, ragged, run_hashes, slices, word_hashes, words_of

WINDOW = 50
# A perfect difference set; every residue modulo 31 is a difference of two members.
PERIOD = 31
COVER = (0, 1, 3, 8, 12, 18)
_SECOND_BASE = 0xA24BAED4963EE407


def _key(docs: DataFrame) -> DataFrame:
    """doc_id, tie (tells texts of one id apart), text."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.hash("text").alias("tie"), F.coalesce("text", F.lit("")).alias("text"))


def _anchor_rows(batches: Iterator[pa.RecordBatch], window: int) -> Iterator[pa.RecordBatch]:
    on_cover = np.zeros(PERIOD, bool)
    on_cover[list(COVER)] = True
    length = window - PERIOD + 1
    for batch in slices(batches):
        words = words_of(batch.column("text"))
        position, counts = words.position(), words.counts()
        room = np.repeat(counts, counts) - position
        at = np.flatnonzero(on_cover[position % PERIOD] & (room >= length) & (np.repeat(counts, counts) >= window))
        if len(at):
            hashes = run_hashes(word_hashes(words.data, words.start, words.end), at, length)
            rows = words.document()[at]
            yield pa.RecordBatch.from_arrays(
                [pa.array(hashes.view(np.int64)), batch.column("doc_id").take(pa.array(rows)), batch.column("tie").take(pa.array(rows)), pa.array(position[at].astype(np.int32))],
                names=["h", "doc_id", "tie", "pos"],
            )


def anchors(keyed: DataFrame, window: int = WINDOW) -> DataFrame:
    """h, doc_id, tie, pos: hashes at cover positions."""
    return keyed.mapInArrow(lambda batches: _anchor_rows(batches, window), "h long, doc_id long, tie int, pos int")


def _digest_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Digest of every whole text; the text itself only where marks ask for a closer look."""
    for batch in slices(batches):
        words = words_of(batch.column("text"))
        body, bounds = joined_words(words)
        unmarked = batch.column("marks").is_null().to_numpy(zero_copy_only=False)
        digests = pa.array([hashlib.sha256(body[a:b]).hexdigest() for a, b in bounds], pa.string())
        text = batch.column("text").take(pa.array(np.arange(batch.num_rows), mask=unmarked))
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("tie"), pa.array(words.counts().astype(np.int64)), digests, text, batch.column("marks")], names=["doc_id", "tie", "n_words", "digest", "text", "marks"])


def _window_rows(batches: Iterator[pa.RecordBatch], window: int) -> Iterator[pa.RecordBatch]:
    for batch in slices(batches):
        words = words_of(batch.column("text"))
        counts = words.counts()
        marks = batch.column("marks")
        per = np.diff(np.asarray(marks.offsets))
        at = marks.flatten().to_numpy() + np.repeat(words.first[:-1], per)
        last = np.repeat(words.first[1:] - window, per)
        starts = np.maximum(at - PERIOD + 1, np.repeat(words.first[:-1], per))
        width = np.maximum(np.minimum(at, last) - starts + 1, 0)
        candidates = np.unique(ragged(starts, width))
        if not len(candidates):
            continue
        hashed = word_hashes(words.data, words.start, words.end)
        rows = pa.array(words.document()[candidates])
        position = candidates - np.repeat(words.first[:-1], counts)[candidates]
        yield pa.RecordBatch.from_arrays(
            [pa.array(run_hashes(hashed, candidates, window).view(np.int64)), pa.array((run_hashes(hashed, candidates, window, _SECOND_BASE) >> np.uint64(32)).astype(np.uint32).view(np.int32)), batch.column("doc_id").take(rows), batch.column("tie").take(rows), pa.array(position.astype(np.int32))],
            names=["h1", "h2", "doc_id", "tie", "pos"],
        )


def _removal_rows(batches: Iterator[pa.RecordBatch], window: int) -> Iterator[pa.RecordBatch]:
    for batch in slices(batches):
        words = words_of(batch.column("text"))
        starts = batch.column("starts")
        per = np.diff(np.asarray(starts.offsets))
        at = starts.flatten().to_numpy() + np.repeat(words.first[:-1], per)
        change = np.zeros(len(words.start) + 1, np.int64)
        np.add.at(change, at, 1)
        np.add.at(change, at + window, -1)
        keep = np.cumsum(change)[:-1] == 0
        body, bounds = joined_words(words, keep)
        removed = np.concatenate([[0], np.cumsum(~keep)])
        digests = [d if not n else hashlib.sha256(body[a:b]).hexdigest() for (a, b), n, d in zip(bounds, per, batch.column("digest").to_pylist(), strict=True)]
        kept = pa.array([str(body[a:b], "utf-8") if n else None for (a, b), n in zip(bounds, per, strict=True)], pa.string())
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(words.counts().astype(np.int64)), pa.array(removed[words.first[1:]] - removed[words.first[:-1]]), pa.array(digests, pa.string()), kept], names=["doc_id", "n_words", "n_removed", "kept_sha256", "kept_text"])


def remove_repeats(docs: DataFrame, window: int = WINDOW, with_text: bool = False) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 (and kept_text where words went) per document row."""
    keyed = _key(docs)
    found = anchors(keyed, window)
    shared = materialize(found.groupBy("h").agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi")).where("lo < hi").select("h"), "anchors")
    marks = found.join(shared, "h").groupBy("doc_id", "tie").agg(F.collect_list("pos").alias("marks"))
    marks = marks.withColumnRenamed("doc_id", "_id").withColumnRenamed("tie", "_tie")
    joined = keyed.join(marks, (keyed["doc_id"] == marks["_id"]) & (keyed["tie"] == marks["_tie"]), "left").select("doc_id", "tie", "text", "marks")
    looked = materialize(joined.mapInArrow(_digest_rows, "doc_id long, tie int, n_words long, digest string, text string, marks array<int>"), "digests")
    release(shared)

    near = looked.where(F.col("text").isNotNull())
    windows = near.select("doc_id", "tie", "text", "marks").mapInArrow(lambda batches: _window_rows(batches, window), "h1 long, h2 int, doc_id long, tie int, pos int")
    first = materialize(windows.groupBy("h1", "h2").agg(F.min("doc_id").alias("first"), F.max("doc_id").alias("last")).where("first < last").select("h1", "h2", "first"), "windows")
    repeats = windows.join(first, ["h1", "h2"]).where("doc_id > first").groupBy("doc_id", "tie").agg(F.collect_set("pos").alias("starts"))
    repeats = repeats.withColumnRenamed("doc_id", "_id").withColumnRenamed("tie", "_tie")
    near = near.select("doc_id", "tie", "text", "digest")
    joined = near.join(repeats, (near["doc_id"] == repeats["_id"]) & (near["tie"] == repeats["_tie"]), "left")
    ready = joined.select("doc_id", "text", "digest", F.coalesce("starts", F.expr("cast(array() as array<int>)")).alias("starts"))
    cut = ready.mapInArrow(lambda batches: _removal_rows(batches, window), "doc_id long, n_words long, n_removed long, kept_sha256 string, kept_text string")
    names = ["doc_id", "n_words", "n_removed", "kept_sha256"] + ["kept_text"] * with_text
    whole = looked.where(F.col("text").isNull()).select("doc_id", "n_words", F.lit(0).cast("long").alias("n_removed"), F.col("digest").alias("kept_sha256"), F.lit(None).cast("string").alias("kept_text"))
    return cut.select(*names).unionByName(whole.select(*names))
