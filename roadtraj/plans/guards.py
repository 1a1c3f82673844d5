"""Size checks before anything is broadcast or collected."""

from __future__ import annotations

from pyspark.sql import DataFrame

MOST_ROWS = 5_000_000


class TooLarge(ValueError):
    """A side meant for every task does not fit; use the join strategy instead."""


def bounded(df: DataFrame, most: int = MOST_ROWS, what: str = "table") -> DataFrame:
    """``df``, once it is known to have at most ``most`` rows."""
    if df.limit(most + 1).count() > most:
        raise TooLarge(f"{what} has more than {most} rows")
    return df
