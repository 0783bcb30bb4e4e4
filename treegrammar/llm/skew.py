"""Joins of many rows with one entry a key, where a few keys may hold most of the rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: A key is hot if it meets more than this part of all rows; so there are at most ``HOT`` hot keys, whatever the size of the tables.
HOT = 1024


def join_entries(rows: DataFrame, entries: DataFrame, on: list[str], weight: str, total: int, how: str = "inner") -> DataFrame:
    """``rows`` joined (inner or left) with ``entries``, which have one row for each key and in ``weight`` the rows that it meets, of ``total``.

    Rows of hot keys stay in place, as their entries (``HOT`` at most) are broadcast; only the others are shuffled by key. Keys are not null."""
    is_hot = F.col(weight) * HOT > total
    hot = F.broadcast(entries.where(is_hot))
    rest = rows.join(hot.select(*on), on, "left_anti").join(entries.where(~is_hot), on, how)
    return rows.join(hot, on).unionByName(rest)
