"""List columns as flat arrays: one function call for a batch, whatever its number of rows.

A column of lists is its values, one after the other, and the offsets of its
rows. Folds over rows take their steps in common: rows go longest first, so the
rows that still have a step are a prefix.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame


def ragged(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Concatenation of the ranges start, start + 1, ... of the given lengths."""
    ends = np.cumsum(lengths)
    return np.arange(int(ends[-1]) if len(ends) else 0) - np.repeat(ends - lengths, lengths) + np.repeat(starts, lengths)


def offsets_of(lengths: np.ndarray) -> np.ndarray:
    return np.concatenate([[0], np.cumsum(lengths)]).astype(np.int64)


def flatten(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Values and offsets; a null list counts as empty."""
    lengths = pc.fill_null(pc.list_value_length(column), 0).to_numpy()
    return column.flatten().to_numpy(zero_copy_only=False), offsets_of(lengths)


def lists(values, offsets: np.ndarray, kind: pa.DataType, like: pa.Array) -> pa.Array:
    """A list column, null where ``like`` is."""
    mask = like.is_null() if like.null_count else None
    return pa.ListArray.from_arrays(pa.array(offsets.astype(np.int32)), pa.array(values, kind) if isinstance(values, np.ndarray) else values, mask=mask)


def steps(offsets: np.ndarray, least: int = 1) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows of ``least`` values and more, longest first: their numbers, first places and lengths."""
    lengths = np.diff(offsets)
    order = np.argsort(-lengths, kind="stable")
    order = order[: int((lengths >= least).sum())]
    return order, offsets[:-1][order], lengths[order]


def alive(lengths: np.ndarray, more_than: int) -> int:
    """How many of the descending lengths exceed a number."""
    return int(np.searchsorted(-lengths, -more_than))


def map_column(df: DataFrame, column: str, shared, function: Callable, kind: str) -> DataFrame:
    """``df`` with ``column`` replaced by function(column, shared value), batch by batch, without a shuffle."""
    schema = ", ".join(f"`{f.name}` {kind if f.name == column else f.dataType.simpleString()}" for f in df.schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        value = shared.value
        for batch in batches:
            done = function(batch.column(column), value)
            yield pa.RecordBatch.from_arrays([done if n == column else batch.column(n) for n in batch.schema.names], names=batch.schema.names)

    return df.mapInArrow(run, schema)
