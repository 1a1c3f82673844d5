"""Hidden Markov language model over documents.

A latent state per token emits a word class, and a class emits a word. The most
frequent words are classes of their own, all others fall into hashed classes, and
words never seen in training are one class. Both numbers of classes grow with the
square root of the vocabulary, so what Baum-Welch gathers grows with the corpus and
still fits into a task; word counts, held in a distributed table, grow with it in
full. Baum-Welch runs over all training documents: tasks sum expected
counts of their sequences, and the sums are added up. The scaled forward
recursion then gives the exact likelihood of every whole document.

Words that are in the head table are looked up where they stand; the rest meet the
word counts in a shuffle join.

Documents share time steps, so a step is one array product. For training, long
texts are worked on in segments at once, and nothing is lost at their borders: the
product of a segment's transitions carries the forward state into the next one
and the backward state into the one before.

Defined results: a null text is one end token; a null doc_id is kept out
of training, and ``held_out`` is null; repeated rows count in training each; other columns are ignored; an
empty table gives an empty table.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from math import ceil, sqrt

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from roadtraj.llm.scratch import materialize
from roadtraj.llm.textbatch import LOWER, ragged, slices, word_hashes, words_of

STATES = 8
OWN_CLASSES = 8  # times the square root of the vocabulary
HASHED_CLASSES = 3  # likewise
HEAD_WORDS = 65_536  # or as many as there are classes of one word
ROUNDS = 3
SEGMENT = 64
TOKENS = 1 << 18  # of the sequences that Baum-Welch works on at once
END = " "  # the end token's entry in the word table; no word holds a space
_LONGEST_HEAD_WORD = 64
_PSEUDO = 0.1


@dataclass(frozen=True)
class Classes:
    """Classes of one word each, hashed classes, and one of unseen words, in this order."""

    own: int
    hashed: int

    @staticmethod
    def of(n_words: int) -> Classes:
        root = ceil(sqrt(n_words)) + 1
        return Classes(OWN_CLASSES * root, HASHED_CLASSES * root)

    @property
    def unseen(self) -> int:
        return self.own + self.hashed

    @property
    def n(self) -> int:
        return self.unseen + 1

    def by_hash(self, hashes: np.ndarray) -> np.ndarray:
        return (self.own + (hashes >> np.uint64(11)) % np.uint64(self.hashed)).astype(np.int32)


def _keyed(docs: DataFrame) -> DataFrame:
    """doc_id, k and tie (96 bits that tell rows apart, but for rows alike in id and text), held_out, text."""
    part = F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(5))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("doc_id", "text").alias("k"), F.hash("text").alias("tie"), (part == 1).alias("held_out"), F.coalesce("text", F.lit("")).alias("text"))


def _strings(data: np.ndarray, start: np.ndarray, end: np.ndarray) -> pa.Array:
    lengths = end - start
    offsets = np.concatenate([[0], np.cumsum(lengths)])
    body = data[ragged(start, lengths)] if len(lengths) else np.zeros(0, np.uint8)
    return pa.LargeStringArray.from_buffers(len(lengths), pa.py_buffer(offsets.astype(np.int64)), pa.py_buffer(np.ascontiguousarray(body))).cast(pa.string())


def _count_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in slices(batches, most=8 << 20):
        words = words_of(batch.column("text"))
        counted = pc.value_counts(_strings(LOWER[words.data], words.start, words.end))
        each, n = counted.field("values"), counted.field("counts")
        yield pa.RecordBatch.from_arrays([pa.concat_arrays([each, pa.array([END])]), pa.concat_arrays([n.cast(pa.int64()), pa.array([batch.num_rows], pa.int64())])], names=["word", "n"])


def word_counts(keyed: DataFrame) -> DataFrame:
    """word, n: training tokens, the end token included."""
    rows = keyed.where(F.coalesce(~F.col("held_out"), F.lit(False))).select("text").mapInArrow(_count_rows, "word string, n long")
    return rows.groupBy("word").agg(F.sum("n").alias("n"))


def hash_of_words(words: list[str]) -> np.ndarray:
    joined = np.frombuffer(b"".join(w.encode() for w in words) or b" ", np.uint8)
    lengths = np.array([len(w.encode()) for w in words], np.int64)
    ends = np.cumsum(lengths)
    return word_hashes(joined, ends - lengths, ends)


class Head:
    """The most frequent words by hash: count and class."""

    def __init__(self, rows: list, kinds: Classes):
        self.kinds = kinds
        hashes = hash_of_words([r["word"] for r in rows])  # rows: most frequent first
        classes = np.where(np.arange(len(rows)) < kinds.own, np.arange(len(rows)), kinds.by_hash(hashes)).astype(np.int32)
        order = np.argsort(hashes)
        self.hashes, self.classes = hashes[order], classes[order]
        self.counts = np.array([r["n"] for r in rows], np.int64)[order]
        at_end = np.flatnonzero(self.hashes == hash_of_words([END])[0])
        self.end = (int(self.classes[at_end[0]]), int(self.counts[at_end[0]])) if len(at_end) else (kinds.unseen, 0)

    def find(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Position in the table, and whether it is there."""
        if not len(self.hashes):
            return np.zeros(len(hashes), np.int64), np.zeros(len(hashes), bool)
        at = np.minimum(np.searchsorted(self.hashes, hashes), len(self.hashes) - 1)
        return at, self.hashes[at] == hashes


_SEQUENCES = "doc_id long, k long, tie int, held_out boolean, classes array<int>, n_head long, base double, inner double, outside array<struct<pos: int, word: string, inner: double>>"


def _sequence_rows(batches: Iterator[pa.RecordBatch], head: Head, inside: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Class sequences, sums over the words in the head table, and the words outside it.

    A word outside has the class it has if training saw it. ``base`` sums
    log10(count + 0.5); ``inner`` sums log10 of the word's share of its class.
    """
    for batch in slices(batches):
        words = words_of(batch.column("text"))
        data = LOWER[words.data]
        hashes = word_hashes(data, words.start, words.end)
        at, known = head.find(hashes)
        counts, n = words.counts(), batch.num_rows
        bounds = np.concatenate([[0], np.cumsum(counts + 1)])
        spot = np.arange(len(at)) + words.document()
        classes, seen = np.full(bounds[-1], head.end[0], np.int64), np.full(bounds[-1], head.end[1], np.int64)
        hashed = head.kinds.by_hash(hashes)
        classes[spot] = np.where(known, head.classes[at], hashed) if len(head.classes) else hashed
        seen[spot] = np.where(known, head.counts[at], 0) if len(head.counts) else 0
        counted = np.ones(bounds[-1], bool)
        counted[spot] = known
        logs = np.log10(seen + 0.5)
        sums = lambda x: np.add.reduceat(np.where(counted, x, 0.0), bounds[:-1]) if n else np.zeros(0)  # noqa: E731, B023
        rest = np.flatnonzero(~known)
        outside = pa.StructArray.from_arrays(
            [pa.array((spot[rest] - np.repeat(bounds[:-1], counts)[rest]).astype(np.int32)), _strings(data, words.start[rest], words.end[rest]), pa.array(-inside[hashed[rest]])], names=["pos", "word", "inner"]
        )
        yield pa.RecordBatch.from_arrays(
            [
                *(batch.column(c) for c in ("doc_id", "k", "tie", "held_out")),
                pa.ListArray.from_arrays(pa.array(bounds.astype(np.int32)), pa.array(classes.astype(np.int32))),
                pa.array(sums(seen > 0).astype(np.int64)), pa.array(sums(logs)), pa.array(sums(np.where(classes == head.kinds.unseen, 0.0, logs - inside[classes]))),
                pa.ListArray.from_arrays(pa.array(np.searchsorted(rest, words.first).astype(np.int32)), outside),
            ],
            names=["doc_id", "k", "tie", "held_out", "classes", "n_head", "base", "inner", "outside"],
        )


def class_totals(counts: DataFrame, head: Head) -> np.ndarray:
    """Tokens and distinct words of every class (classes x 2), from the whole word table."""
    kinds = head.kinds

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((kinds.n, 2), np.int64)
        for batch in batches:
            n = batch.column("n").to_numpy()
            hashes = word_hashes(*_bounds(batch.column("word")))
            at, known = head.find(hashes)
            classes = np.where(known, head.classes[at] if len(head.classes) else 0, kinds.by_hash(hashes))
            np.add.at(total[:, 0], classes, n)
            np.add.at(total[:, 1], classes, 1)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(kinds.n)), pa.array(total[:, 0]), pa.array(total[:, 1])], names=["c", "n", "v"])

    out = np.zeros((kinds.n, 2), np.int64)
    for r in counts.mapInArrow(sums, "c long, n long, v long").groupBy("c").agg(F.sum("n").alias("n"), F.sum("v").alias("v")).collect():
        out[r["c"]] = r["n"], r["v"]
    return out


def _bounds(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    from roadtraj.llm.textbatch import text_bytes

    data, offsets = text_bytes(column)
    return data, offsets[:-1], offsets[1:]


class Model:
    """start (K), move (K x K) and emit (C x K) probabilities."""

    def __init__(self, start: np.ndarray, move: np.ndarray, emit: np.ndarray):
        self.start, self.move, self.emit = start, move, emit

    @staticmethod
    def initial(class_tokens: np.ndarray, seed: int = 11) -> Model:
        """Class frequencies, disturbed differently for each state, and sticky states."""
        rng = np.random.default_rng(seed)
        emit = (class_tokens[:, None] + _PSEUDO) * rng.gamma(1.0, 1.0, (len(class_tokens), STATES))
        move = np.full((STATES, STATES), 0.1 / STATES) + 0.9 * np.eye(STATES)
        return Model(np.full(STATES, 1 / STATES), move / move.sum(1, keepdims=True), emit / emit.sum(0))

    @staticmethod
    def from_counts(start: np.ndarray, move: np.ndarray, emit: np.ndarray) -> Model:
        start, move, emit = start + _PSEUDO, move + _PSEUDO, emit + _PSEUDO / 10
        emit[-1] = 0  # the class of unseen words, whose share is set apart
        return Model(start / start.sum(), move / move.sum(1, keepdims=True), emit / emit.sum(0))


def _by_length(flat: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows longest first: their order, first places, and how many rows are alive at each step."""
    lengths = np.diff(bounds)
    order = np.argsort(-lengths, kind="stable")
    sorted_ = lengths[order]
    alive = np.searchsorted(-sorted_, -np.arange(1, (sorted_[0] if len(sorted_) else 0) + 1), side="right")
    return order, bounds[:-1][order], alive


def forward(model: Model, flat: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Natural log likelihood of each class sequence, by the scaled forward recursion in lock step."""
    order, first, alive = _by_length(flat, bounds)
    total = np.zeros(len(order))
    state = np.repeat(model.start[None, :], len(order), axis=0)
    for t, n in enumerate(alive):
        state = (state[:n] if t == 0 else state[:n] @ model.move) * model.emit[flat[first[:n] + t]]
        scale = state.sum(1)
        state /= scale[:, None]
        total[:n] += np.log(scale)
    out = np.empty(len(order))
    out[order] = total
    return out


def _segments(bounds: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """Bounds of the segments of all sequences, and the number of each in its sequence."""
    per = -(-np.diff(bounds) // length)
    number = ragged(np.zeros(len(per), np.int64), per)
    return np.concatenate([np.repeat(bounds[:-1], per) + number * length, bounds[-1:]]), number


def _transitions(model: Model, flat: np.ndarray, cuts: np.ndarray, which: np.ndarray) -> np.ndarray:
    """Products of move and emission over all tokens of some segments (segments x K x K), each scaled."""
    lengths = np.diff(cuts)[which]
    order = np.argsort(-lengths, kind="stable")
    first, alive = cuts[:-1][which][order], np.searchsorted(-lengths[order], -np.arange(1, lengths.max(initial=0) + 1), side="right")
    n_states = len(model.start)
    product = np.repeat(np.eye(n_states)[None], len(which), axis=0)
    for t, n in enumerate(alive):
        step = (product[:n].reshape(-1, n_states) @ model.move).reshape(n, n_states, n_states) * model.emit[flat[first[:n] + t]][:, None, :]
        product[:n] = step / step.sum((1, 2), keepdims=True)
    out = np.empty_like(product)
    out[order] = product
    return out


def _border_states(model: Model, flat: np.ndarray, cuts: np.ndarray, number: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Forward state before each segment, and backward state behind it, each up to a factor.

    Before the first segment of a sequence the state is the model's start, behind the last one it is 1.
    """
    n_states = len(model.start)
    before, behind = np.zeros((len(number), n_states)), np.ones((len(number), n_states))
    later = np.flatnonzero(number > 0)
    if not len(later):
        return before, behind
    product = np.zeros((len(number), n_states, n_states))
    product[later] = _transitions(model, flat, cuts, later)
    opening = later[number[later] == 1] - 1  # first segments that have a second
    state = np.repeat(model.start[None, :], len(opening), axis=0) * model.emit[flat[cuts[opening]]]
    for t in range(1, int(np.diff(cuts)[opening].max())):
        state = (state @ model.move) * model.emit[flat[cuts[opening] + t]]
        state /= state.sum(1, keepdims=True)
    before[opening + 1] = state / state.sum(1, keepdims=True)
    for k in range(2, int(number.max()) + 1):
        at = np.flatnonzero(number == k)
        onward = (before[at - 1][:, None, :] @ product[at - 1])[:, 0, :]
        before[at] = onward / onward.sum(1, keepdims=True)
    for k in range(int(number.max()), 0, -1):
        at = np.flatnonzero(number == k)
        back = (product[at] @ behind[at][:, :, None])[:, :, 0]
        behind[at - 1] = back / back.sum(1, keepdims=True)
    return before, behind


def expected_counts(model: Model, flat: np.ndarray, bounds: np.ndarray, length: int | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
    """Baum-Welch: expected starts, moves and emissions over whole sequences, and their log likelihood.

    Segments of ``length`` tokens are worked on side by side; states at their borders are exact.
    """
    cuts, number = _segments(bounds, length or SEGMENT)
    before, behind = _border_states(model, flat, cuts, number)
    n_states = len(model.start)
    order, first, alive = _by_length(flat, cuts)
    before, behind, opens = before[order], behind[order], (number == 0)[order]
    lengths = np.diff(cuts)[order]
    start, move, emit, total = np.zeros(n_states), np.zeros((n_states, n_states)), np.zeros_like(model.emit), 0.0
    ahead, scales = [], []
    state = np.where(opens[:, None], model.start[None, :], before @ model.move)
    for t, n in enumerate(alive):
        state = (state if t == 0 else state[:n] @ model.move) * model.emit[flat[first[:n] + t]]
        scale = state.sum(1)
        state = state / scale[:, None]
        total += np.log(scale).sum()
        ahead.append(state)
        scales.append(scale)
    classes, weights = [], []
    back = np.zeros((0, n_states))
    for t in range(len(alive) - 1, -1, -1):
        n = alive[t]
        m = alive[t + 1] if t + 1 < len(alive) else 0
        grown = np.empty((n, n_states))
        grown[m:] = behind[m:n]  # segments that end here
        grown[m:] /= (ahead[t][m:] * grown[m:]).sum(1, keepdims=True)
        if m:
            seen = model.emit[flat[first[:m] + t + 1]] * back / scales[t + 1][:, None]
            move += (ahead[t][:m].T @ seen) * model.move
            grown[:m] = seen @ model.move.T
        back = grown
        classes.append(flat[first[:n] + t])
        weights.append(ahead[t] * back)
    if classes:
        start += weights[-1][opens[: alive[0]]].sum(0)
        follows = np.flatnonzero(~opens)
        seen = model.emit[flat[first[follows]]] * back[follows] / scales[0][follows][:, None]
        move += (before[follows].T @ seen) * model.move
        where, weight = np.concatenate(classes), np.concatenate(weights)
        for k in range(n_states):
            emit[:, k] = np.bincount(where, weights=weight[:, k], minlength=len(emit))
    return start, move, emit, total


def _flat(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    offsets = np.asarray(column.offsets).astype(np.int64)
    return column.flatten().to_numpy(), offsets - offsets[0]


def train(sequences: DataFrame, model: Model, rounds: int = ROUNDS) -> tuple[Model, list[float]]:
    """Baum-Welch over all training sequences; the log likelihood before each round."""
    seen, training = [], sequences.where(F.coalesce(~F.col("held_out"), F.lit(False))).select("classes")
    for _ in range(rounds):
        now = sequences.sparkSession.sparkContext.broadcast((model.start, model.move, model.emit))

        def gather(batches: Iterator[pa.RecordBatch], now=now) -> Iterator[pa.RecordBatch]:
            here, sums = Model(*now.value), None
            for batch in batches:
                flat, bounds = _flat(batch.column("classes"))
                lo = 0
                while lo + 1 < len(bounds):  # whole sequences, TOKENS or one at once
                    hi = max(lo + 1, int(np.searchsorted(bounds, bounds[lo] + TOKENS, side="right")) - 1)
                    got = expected_counts(here, flat, bounds[lo : hi + 1])
                    sums = got if sums is None else tuple(a + b for a, b in zip(sums, got, strict=True))
                    lo = hi
            if sums is not None:
                flat = np.concatenate([sums[0], sums[1].ravel(), sums[2].ravel(), [sums[3]]])
                at = np.flatnonzero(flat)
                yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(flat[at])], names=["cell", "weight"])

        n_states, n_classes = len(model.start), len(model.emit)
        flat = np.zeros(n_states + n_states**2 + n_classes * n_states + 1)
        for r in training.mapInArrow(gather, "cell long, weight double").groupBy("cell").agg(F.sum("weight").alias("weight")).toPandas().itertuples():
            flat[r.cell] = r.weight
        start, move, emit, (total,) = np.split(flat, np.cumsum([n_states, n_states**2, n_classes * n_states]))
        model = Model.from_counts(start, move.reshape(n_states, n_states), emit.reshape(n_classes, n_states))
        seen.append(float(total))
        now.unpersist()
    return model, seen


def outside_words(found: DataFrame, counts: DataFrame) -> DataFrame:
    """_k, _tie, rows, n_known, base, inner, unseen (places) of the words outside the head, from the word table."""
    each = found.select("k", "tie", F.explode("outside").alias("o")).select("k", "tie", "o.*")
    met = each.join(counts, "word", "left")
    summed = met.groupBy("k", "tie").agg(
        F.count(F.lit(1)).alias("rows"),
        F.count("n").alias("n_known"),
        F.sum(F.log10(F.coalesce("n", F.lit(0)) + 0.5)).alias("o_base"),
        F.sum(F.when(F.col("n").isNotNull(), F.log10(F.col("n") + 0.5) + F.col("inner")).otherwise(0.0)).alias("o_inner"),
        F.collect_set(F.when(F.col("n").isNull(), F.col("pos"))).alias("unseen"),
    )
    return summed.withColumnRenamed("k", "_k").withColumnRenamed("tie", "_tie")


def frequent_words(counts: DataFrame, most: int = HEAD_WORDS) -> list:
    """Rows of the most frequent words, at most ``most`` of them, by count, then word.

    A histogram of counts on a log scale, whose size is fixed, gives the level
    that no more than ``most`` words reach; only those come to the driver.
    """
    level = F.floor(F.log2("n") * 32)
    short = counts.where(F.octet_length("word") <= _LONGEST_HEAD_WORD)
    room, cut = most, 1 << 20
    for r in sorted(short.groupBy(level.alias("level")).count().collect(), key=lambda r: -r["level"]):
        if r["count"] > room:
            break
        room, cut = room - r["count"], r["level"]
    return sorted(short.where(level >= cut).collect(), key=lambda r: (-r["n"], r["word"]))


def _unseen_share(counts: DataFrame, total: int) -> float:
    """The share of tokens that are new words: that of words seen once."""
    once = counts.where("n = 1").count()
    return min(max(once / total, 1e-9), 0.5) if total else 1.0


def score(docs: DataFrame, rounds: int = ROUNDS) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of each document row.

    ``base_score`` is the smoothed word frequency model; ``score`` the log10
    probability of the text under the hidden Markov model.
    """
    spark = docs.sparkSession
    keyed = _keyed(docs)
    counts = materialize(word_counts(keyed), "counts")
    facts = counts.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.count(F.lit(1)).alias("v")).first()
    n_all, n_kinds = int(facts["n"]), int(facts["v"])
    kinds = Classes.of(n_kinds)
    head = Head(frequent_words(counts, max(HEAD_WORDS, kinds.own)), kinds)
    totals = class_totals(counts, head)
    inside = np.log10(np.maximum(totals[:, 0] + 0.5 * totals[:, 1], 0.5))
    found = materialize(keyed.mapInArrow(lambda batches: _sequence_rows(batches, head, inside), _SEQUENCES), "sequences")
    model, _ = train(found, Model.initial(totals[:, 0]), rounds)
    unseen = _unseen_share(counts, n_all)
    emit = model.emit * (1 - unseen)
    emit[kinds.unseen] = unseen
    parts = spark.sparkContext.broadcast((model.start, model.move, emit))

    outside = outside_words(found, counts)
    flat = found.select("doc_id", "k", "tie", "held_out", "classes", "n_head", "base", "inner", F.size("outside").alias("n_outside"))
    joined = flat.join(outside, (flat["k"] == outside["_k"]) & (flat["tie"] == outside["_tie"]), "left")

    def rate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here = Model(*parts.value)
        for batch in batches:
            classes, bounds = _flat(batch.column("classes"))
            classes = classes.astype(np.int64)
            marks, mark_bounds = _flat(batch.column("unseen"))
            classes[marks + np.repeat(bounds[:-1], np.diff(mark_bounds))] = kinds.unseen
            logs = forward(here, classes, bounds) / np.log(10)
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("doc_id", "held_out")), pa.array(np.diff(bounds)), *(batch.column(c) for c in ("n_known", "base", "inner")), pa.array(logs)], names=["doc_id", "held_out", "n_tokens", "n_known", "base", "inner", "logs"])

    share = F.coalesce(F.col("n_outside") / F.col("rows"), F.lit(0.0))  # repeated rows met the table together
    ready = joined.select(
        "doc_id", "held_out", "classes",
        (F.col("n_head") + F.coalesce(F.round(F.col("n_known") * share), F.lit(0.0))).cast("long").alias("n_known"),
        (F.col("base") + F.coalesce(F.col("o_base") * share, F.lit(0.0))).alias("base"),
        (F.col("inner") + F.coalesce(F.col("o_inner") * share, F.lit(0.0))).alias("inner"),
        F.coalesce("unseen", F.expr("cast(array() as array<int>)")).alias("unseen"),
    )
    rated = ready.mapInArrow(rate, "doc_id long, held_out boolean, n_tokens long, n_known long, base double, inner double, logs double")
    level = float(np.log10(n_all + 0.5 * (n_kinds + 1)))
    return rated.select(
        "doc_id", "held_out", "n_tokens", "n_known", F.lit(n_all).cast("long").alias("train_tokens"),
        (F.col("base") - F.col("n_tokens") * level).alias("base_score"), (F.col("logs") + F.col("inner")).alias("score"),
    )
