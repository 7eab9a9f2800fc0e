"""Broadcast joins behind a check of the size of the small side."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Rows up to which a side may be broadcast; beyond it the join is left to shuffles.
MAX_BROADCAST_ROWS = 200_000


def fits(df: DataFrame, max_rows: int = MAX_BROADCAST_ROWS) -> bool:
    """Whether df has at most max_rows rows; reads no more than one row beyond that."""
    return df.limit(max_rows + 1).count() <= max_rows


def checked_join(
    big: DataFrame, small: DataFrame, on: Column | str | list[str], how: str = "inner", max_rows: int = MAX_BROADCAST_ROWS
) -> DataFrame:
    """big ⋈ small: a broadcast join while small fits, else a shuffled one that AQE may split on skew."""
    return big.join(F.broadcast(small) if fits(small, max_rows) else small, on, how)
