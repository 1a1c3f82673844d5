"""Sum-of-squares online packing of tokenised documents into windows.

A window of fixed length is open while partly filled. The level array counts the
open windows of each fill level; a piece of length s goes to the level (0: a new
window) whose change makes the sum of squared counts smallest. Each task packs
its own rows with its own array. Documents longer than a window are cut into
full windows and a rest. When a task's rows end, its open windows stay as the level
array left them where they are ENOUGH full, so that none of them is padded by more;
only the tokens of emptier ones are cut anew, which leaves one window per task that
may be. ``padding`` tells what either way comes to.

Defined results: a null text is empty and yields its end token alone; repeated
rows are packed each; columns beyond doc_id and text are ignored; an empty table
gives an empty table.
"""

from __future__ import annotations

import os
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from roadtraj.llm.textbatch import LOWER, Words, ragged, slices, word_hashes, words_of

WINDOW = 2048
ENOUGH = 7 / 8
END_ID = 1
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
_PIECES = pa.schema([(n, pa.int64()) for n in ("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")])


_LETTER = np.zeros(256, bool)
_LETTER[97:123] = True
_STOP = np.zeros(256, bool)
_STOP[[44, 46]] = True


def _parts(words: Words) -> Words:
    """Words in lower case, a last comma or full stop after a letter apart: fewer distinct ones, the same ids."""
    data, start, end = LOWER[words.data], words.start, words.end
    marked = np.unique(np.searchsorted(start, np.flatnonzero(words.data == 60), side="right") - 1)
    if len(marked):  # may hold a special token's string, which capitals are not
        at = ragged(start[marked], end[marked] - start[marked])
        data[at] = words.data[at]
    last, before = data[np.maximum(end - 1, 0)] if len(end) else end, data[np.maximum(end - 2, 0)] if len(end) else end
    cut = (end - start > 1) & _STOP[last] & _LETTER[before] if len(end) else np.zeros(0, bool)
    each = 1 + cut.astype(np.int64)
    starts, ends, stops = np.repeat(start, each), np.repeat(end, each), np.cumsum(each)
    starts[stops[cut] - 1] = ends[stops[cut] - 2] = end[cut] - 1
    return Words(data, starts, ends, np.concatenate([[0], stops])[words.first])


# Texts on which a tokenizer must treat words one by one, in lower case, for ``WordTokenizer`` to use that.
_PROBES = ("Ab cD", "a\tb\n\nc  d\x0b\x0ce\r", " lead trail ", "end. next, x.y z,", "It's DON'T", "1.5 2,000 a1.", "\u00c9t\u00e9 \u00df \u0130", "a-b (c) \"d\"", "<x> &amp; #t @u", "!a b! !", "\u4f60\u597d \U0001f600 a")


class WordTokenizer:
    """Token ids of texts through their distinct words.

    Where the tokenizer treats words one by one (probed at the start), the ids of
    words already met are held by the words' 64-bit hashes, up to ``most`` words;
    then the store starts anew. Any other tokenizer gets the whole texts.
    """

    def __init__(self, path: str, most: int = 1_000_000):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer, self.most = Tokenizer.from_file(path), most
        mark = self.tokenizer.encode("!", add_special_tokens=False).ids
        self.mark = mark[0] if len(mark) == 1 else None
        self._clear()
        self.by_word = all(np.array_equal(self._whole(pa.array([p]))[0], self._words(pa.array([p]))[0]) for p in _PROBES)
        self._clear()

    def _whole(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """As ``encode``, without the store of words."""
        found = [e.ids for e in self.tokenizer.encode_batch_fast([t or "" for t in column.to_pylist()], add_special_tokens=False)]
        return np.array([i for ids in found for i in ids], np.uint32), np.concatenate([[0], np.cumsum([len(ids) for ids in found])]).astype(np.int64)

    def _clear(self) -> None:
        self.hashes, self.firsts, self.sizes = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
        self.table = np.zeros(0, np.uint32)

    def _find(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if not len(self.hashes):
            return np.zeros(len(hashes), np.int64), np.zeros(len(hashes), bool)
        at = np.minimum(np.searchsorted(self.hashes, hashes), len(self.hashes) - 1)
        return at, self.hashes[at] == hashes

    def _learn(self, words: Words, hashes: np.ndarray, new: np.ndarray) -> None:
        fresh, first = np.unique(hashes[new], return_index=True)
        body = words.data.tobytes()
        texts = [body[a:b].decode() for a, b in zip(words.start[new[first]].tolist(), words.end[new[first]].tolist(), strict=True)]
        marked = np.array([self.mark is None or "!" in t for t in texts])
        order = np.concatenate([np.flatnonzero(~marked), np.flatnonzero(marked)])
        plain, rest = [texts[i] for i in order[: len(texts) - marked.sum()]], [texts[i] for i in np.flatnonzero(marked)]
        # Words in lines, parted by a mark whose id no word among them has: far fewer texts than words.
        lines = [" ! ".join(plain[lo : lo + 64]) for lo in range(0, len(plain), 64)]
        parts, sizes = [], []
        for lo in range(0, len(lines), 512):
            for e in self.tokenizer.encode_batch_fast(lines[lo : lo + 512], add_special_tokens=False):
                parts.append(np.array([*e.ids, self.mark], np.uint32))
        coded = np.concatenate([np.zeros(0, np.uint32), *parts])
        stops = np.flatnonzero(coded == self.mark) if len(coded) else np.zeros(0, np.int64)
        sizes = np.diff(stops, prepend=-1) - 1
        single = [np.array(e.ids, np.uint32) for e in self.tokenizer.encode_batch_fast(rest, add_special_tokens=False)]
        sizes = np.concatenate([sizes, np.array([len(x) for x in single], np.int64)])
        firsts = len(self.table) + np.cumsum(sizes) - sizes
        self.table = np.concatenate([self.table, np.delete(coded, stops), *single])
        into = np.argsort(all_ := np.concatenate([self.hashes, fresh[order]]), kind="stable")
        self.hashes, self.firsts, self.sizes = all_[into], np.concatenate([self.firsts, firsts])[into], np.concatenate([self.sizes, sizes])[into]

    def encode(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """All ids and each text's bounds in them."""
        return self._words(column) if self.by_word else self._whole(column)

    def _words(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        words = _parts(words_of(column))
        hashes = word_hashes(words.data, words.start, words.end)
        if len(self.hashes) > self.most:
            self._clear()
        at, known = self._find(hashes)
        if not known.all():
            old = at[known]
            before = self.hashes
            self._learn(words, hashes, new := np.flatnonzero(~known))
            moved = np.searchsorted(self.hashes, before)  # where the words known before stand now
            at[known] = moved[old]
            at[new], _ = self._find(hashes[new])
        per = self.sizes[at] if len(at) else np.zeros(0, np.int64)
        ids = self.table[ragged(self.firsts[at], per)] if len(at) else np.zeros(0, np.uint32)
        return ids, np.concatenate([[0], np.cumsum(per)])[words.first]


class LevelArray:
    """Open windows by fill level; ``place`` puts one piece where the squared counts grow least."""

    def __init__(self, window: int):
        self.window = window
        self.counts = np.zeros(window + 1, np.int64)
        self.at: list[list[list]] = [[] for _ in range(window)]

    def place(self, length: int, piece) -> list | None:
        """The pieces of the window that this piece fills, else None."""
        gain = 2 * self.counts[length:] + 1
        gain[-1] = 0  # a full window is no longer counted
        stay = self.counts[: self.window - length + 1]
        change = np.where(stay > 0, gain - 2 * stay + 1, np.iinfo(np.int64).max)
        change[0] = gain[0]
        level = int(change.argmin())
        if level:
            self.counts[level] -= 1
            bin_ = self.at[level].pop()
        else:
            bin_ = []
        bin_.append(piece)
        if level + length == self.window:
            return bin_
        self.counts[level + length] += 1
        self.at[level + length].append(bin_)
        return None

    def rest(self) -> Iterator[list]:
        for level in range(self.window - 1, 0, -1):
            yield from self.at[level]


class _Writer:
    def __init__(self, task: int):
        self.next, self.rows = task << 33, []

    def window(self, pieces: list) -> None:
        offset = 0
        for doc, start, ids, total in pieces:
            self.rows.append((doc, start, len(ids), zlib.crc32(ids.astype("<u4").tobytes()), total, self.next, offset))
            offset += len(ids)
        self.next += 1

    def batch(self) -> pa.RecordBatch:
        columns, self.rows = list(zip(*self.rows, strict=True)), []
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], schema=_PIECES)


def _recut(windows: Iterator[list], window: int) -> Iterator[list]:
    """The pieces of open windows cut anew into full windows and one last window."""
    out, room = [], window
    for doc, start, ids, total in (p for w in windows for p in w):
        while len(ids):
            part, ids = ids[:room], ids[room:]
            out.append((doc, start, part, total))
            start, room = start + len(part), room - len(part)
            if not room:
                yield out
                out, room = [], window
    if out:
        yield out


def _pack(batches: Iterator[pa.RecordBatch], path: str, window: int) -> Iterator[pa.RecordBatch]:
    from pyspark import TaskContext

    writer, levels, tokenizer = _Writer(TaskContext.get().partitionId()), LevelArray(window), WordTokenizer(path)
    for batch in slices(batches, most=4 << 20):
        ids, bounds = tokenizer.encode(batch.column("text"))
        for n, doc in enumerate(batch.column("doc_id").to_pylist()):
            tokens = np.append(ids[bounds[n] : bounds[n + 1]], np.uint32(END_ID))
            for start in range(0, len(tokens), window):
                piece = (doc, start, tokens[start : start + window], len(tokens))
                filled = [piece] if len(piece[2]) == window else levels.place(len(piece[2]), piece)
                if filled:
                    writer.window(filled)
        if writer.rows:
            yield writer.batch()
    sparse = []
    for pieces in levels.rest():
        if sum(len(p[2]) for p in pieces) >= ENOUGH * window:
            writer.window(pieces)
        else:
            sparse.append(pieces)
    for pieces in _recut(iter(sparse), window):
        writer.window(pieces)
    if writer.rows:
        yield writer.batch()


def pack(docs: DataFrame, tokenizer_path: str, window: int = WINDOW) -> DataFrame:
    """One row per piece (see PIECES): its document's tokens, its place in a sequence, padding at the end of sequences."""
    return docs.select(F.col("doc_id").cast("long"), F.col("text")).mapInArrow(lambda batches: _pack(batches, tokenizer_path, window), PIECES)


def padding(packed: DataFrame, window: int = WINDOW) -> DataFrame:
    """sequences, tokens, padded (places without a token), worst (most of them in one sequence) of what ``pack`` returns."""
    filled = packed.groupBy("sequence_id").agg(F.sum("length").alias("n"))
    return filled.agg(F.count(F.lit(1)).alias("sequences"), F.sum("n").alias("tokens"), F.sum(F.lit(window) - F.col("n")).alias("padded"), F.max(F.lit(window) - F.col("n")).alias("worst"))
