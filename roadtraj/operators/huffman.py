"""Huffman codebook over the gram dictionary.

The dictionary, whose size is checked, is merged on the driver with two queues;
the codes are canonical, so lengths alone give them back. What tasks get are arrays:
the trie that finds a gram from its edges, code words, and the edges of each gram.
"""

from __future__ import annotations

from collections import deque
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from roadtraj.operators.flat import offsets_of, ragged
from roadtraj.plans.guards import TooLarge

MOST_BYTES = 512 << 20  # of a codebook in a task; some 80 for each gram and its text
MOST_BITS = 57  # of a code word, so that it is read from eight bytes at any bit


def code_lengths(weights: list[int]) -> list[int]:
    """Code length of each weight; ``weights`` ascend."""
    n = len(weights)
    if n < 2:
        return [1] * n
    leaves, joined = deque((w, i) for i, w in enumerate(weights)), deque()
    parent = [0] * (2 * n - 1)
    for at in range(n, 2 * n - 1):
        total = 0
        for _ in range(2):
            queue = leaves if not joined or (leaves and leaves[0][0] <= joined[0][0]) else joined
            w, i = queue.popleft()
            parent[i], total = at, total + w
        joined.append((total, at))
    depth = [0] * (2 * n - 1)
    for i in range(2 * n - 3, -1, -1):
        depth[i] = depth[parent[i]] + 1
    return depth[:n]


class Codebook:
    """Canonical codes of grams: shorter codes first, then by gram. Grams are numbered in that order."""

    def __init__(self, grams: list[tuple[str, int]], theta: int):
        ordered = sorted(grams, key=lambda g: (g[1], -g[0].count("-"), g[0]))
        bits = code_lengths([f for _, f in ordered])
        book = sorted(zip(bits, (g for g, _ in ordered), (f for _, f in ordered), strict=True))
        self.theta = theta
        self.names = pa.array([g for _, g, _ in book], pa.string())
        self.bits, self.weights = np.array([n for n, _, _ in book], np.int64), np.array([f for _, _, f in book], np.int64)
        if self.bits.max(initial=0) > MOST_BITS:
            raise ValueError(f"code words of more than {MOST_BITS} bits")
        # Each code word is the one before plus one, with zeros for what it is longer.
        self.words = np.zeros(len(book), np.int64)
        for i in range(1, len(book)):
            self.words[i] = (self.words[i - 1] + 1) << (self.bits[i] - self.bits[i - 1])
        parts = [[int(e) for e in g.split("-")] for _, g, _ in book]
        self.edges, self.starts = np.array([e for p in parts for e in p], np.int32), offsets_of([len(p) for p in parts])
        self.symbols = int(self.edges.max(initial=-1)) + 1
        number = {g: i for i, (_, g, _) in enumerate(book)}
        parent = np.array([number[g.rpartition("-")[0]] if "-" in g else -1 for _, g, _ in book], np.int64)
        key = (parent + 1) * self.symbols + np.array([p[-1] for p in parts], np.int64)
        self.children = np.argsort(key, kind="stable")
        self.keys = key[self.children]

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k not in ("freq", "lengths", "codes")}

    @cached_property
    def freq(self) -> dict[str, int]:
        return dict(zip(self.names.to_pylist(), self.weights.tolist(), strict=True))

    @cached_property
    def lengths(self) -> dict[str, int]:
        return dict(zip(self.names.to_pylist(), self.bits.tolist(), strict=True))

    @cached_property
    def codes(self) -> dict[str, int]:
        return dict(zip(self.names.to_pylist(), self.words.tolist(), strict=True))

    def total_bits(self) -> int:
        return int((self.bits * self.weights).sum())

    def onward(self, gram: np.ndarray, edge: np.ndarray) -> np.ndarray:
        """The grams one edge longer (gram -1: the edge alone), -1 where the dictionary has none."""
        key = (gram + 1) * self.symbols + edge
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        known = (self.keys[at] == key) & (edge < self.symbols) & (edge >= 0)
        return np.where(known, self.children[at], -1)

    def pack(self, grams: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Bytes of all rows, their offsets, and the number of bits of each row."""
        size = self.bits[grams]
        upto = offsets_of(size)
        n_bits = np.diff(upto[offsets])
        bounds = offsets_of((n_bits + 7) // 8)
        start = upto[:-1] + np.repeat(bounds[:-1] * 8 - upto[offsets[:-1]], np.diff(offsets))
        out = np.zeros(int(bounds[-1]) * 8, np.uint8)
        shift = np.repeat(size, size) - 1 - ragged(np.zeros(len(size), np.int64), size)
        out[ragged(start, size)] = np.repeat(self.words[grams], size) >> shift & 1
        return np.packbits(out), bounds, n_bits

    def unpack(self, data: np.ndarray, bounds: np.ndarray, n_bits: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Grams of all rows and their offsets: every step reads one code word of each row."""
        widths, first = np.unique(self.bits, return_index=True)
        count = np.diff(np.append(first, len(self.bits)))
        spare = (64 - widths).astype(np.uint64)
        last = (self.words[first] + count - 1).astype(np.uint64)
        limit = (last << spare) | ((np.uint64(1) << spare) - np.uint64(1))  # the greatest 64 bits that begin with such a word
        body = np.concatenate([data, np.zeros(8, np.uint8)])
        row, at, rows, grams = np.arange(len(n_bits)), bounds[:-1] * 8, [], []
        end = at + n_bits
        while True:
            more = at < end
            if not more.any():
                break
            row, at, end = row[more], at[more], end[more]
            eight = np.ascontiguousarray(body[(at >> 3)[:, None] + np.arange(8)]).view(">u8")[:, 0].astype(np.uint64)
            window = eight << (at & 7).astype(np.uint64)
            kind = np.searchsorted(limit, window)
            word = (window >> spare[kind]).astype(np.int64)
            rows.append(row)
            grams.append(first[kind] + word - self.words[first[kind]])
            at = at + widths[kind]
        if not rows:
            return np.zeros(0, np.int64), np.zeros(len(n_bits) + 1, np.int64)
        row = np.concatenate(rows)
        return np.concatenate(grams)[np.argsort(row, kind="stable")], offsets_of(np.bincount(row, minlength=len(n_bits)))

    def expand(self, grams: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The edges of all rows of grams, and their offsets."""
        size = np.diff(self.starts)[grams]
        return self.edges[ragged(self.starts[grams], size)], offsets_of(size)[offsets]

    def rows(self, spark: SparkSession) -> DataFrame:
        """gram, freq, code_len, code."""
        data = [(g, f, n, format(c, f"0{n}b")) for g, f, n, c in zip(self.names.to_pylist(), self.weights.tolist(), self.bits.tolist(), self.words.tolist(), strict=True)]
        return spark.createDataFrame(data, "gram string, freq long, code_len int, code string")


def codebook(grams: DataFrame, theta: int, most: int = MOST_BYTES) -> Codebook:
    """The codebook of a dictionary (gram, freq). Its bytes are checked before any of it is collected."""
    size = grams.agg(F.coalesce(F.sum(F.octet_length("gram") + 80), F.lit(0)).alias("bytes")).first()["bytes"]
    if size > most:
        raise TooLarge(f"the gram dictionary has {size} bytes, more than {most}; mine with a higher min_freq")
    rows = grams.select("gram", "freq").toArrow()
    return Codebook(list(zip(rows.column("gram").to_pylist(), rows.column("freq").to_pylist(), strict=True)), theta)


def entropy_bounds(book: Codebook) -> tuple[float, float]:
    """Entropy of the dictionary's weights, and the mean code length; the second is less than the first plus 1."""
    total = int(book.weights.sum())
    share = book.weights[book.weights > 0] / total
    return float(-(share * np.log2(share)).sum()), book.total_bits() / total


def refresh(old: DataFrame, new_counts: DataFrame) -> DataFrame:
    """Dictionary of old and new counts added, for a codebook trained anew."""
    return old.select("gram", "n", "freq").unionByName(new_counts.select("gram", "n", "freq")).groupBy("gram", "n").agg(F.sum("freq").alias("freq"))


def write_version(grams: DataFrame, path: str, version: int) -> None:
    """Keep a dictionary as one version of several; what was packed with it names the version."""
    grams.select("gram", "n", "freq").write.mode("overwrite").parquet(f"{path}/version={version}")


def read_version(spark: SparkSession, path: str, version: int | None = None) -> tuple[int, DataFrame]:
    """A version and its dictionary; the last one if none is named."""
    stored = spark.read.parquet(path)
    if version is None:
        version = stored.agg(F.max("version")).first()[0]
    return int(version), stored.where(F.col("version") == version).drop("version")
