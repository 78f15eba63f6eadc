"""Joins that stay even where a key holds a large share of all rows, and joins with small sides behind a count."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: At most so many rows of keys go into a broadcast; beyond that the join is dealt out.
BROADCAST_KEYS = 300_000
#: A key with more rows than this, and than a 100,000th of all rows, is heavy. So at most 100,000 keys are.
HEAVY_ROWS, HEAVY_SHARE = 4096, 100_000


def _small(keys: DataFrame, limit: int) -> DataFrame:
    return F.broadcast(keys) if keys.count() <= limit else keys


def only(df: DataFrame, keys: DataFrame, on: str | list[str] | Column, limit: int = BROADCAST_KEYS) -> DataFrame:
    """Rows of ``df`` whose key is in ``keys`` (a small set is sent whole, after it was counted)."""
    return df.join(_small(keys, limit), on, "left_semi")


def without(df: DataFrame, keys: DataFrame, on: str | list[str] | Column, limit: int = BROADCAST_KEYS) -> DataFrame:
    """Rows of ``df`` whose key is not in ``keys``."""
    return df.join(_small(keys, limit), on, "left_anti")


def join_counted(left: DataFrame, right: DataFrame, on: Sequence[str], n: str = "n") -> DataFrame:
    """``left`` with the columns of ``right`` (left outer), where ``right`` has one row for each key, and in ``n`` how many rows of ``left`` have it.

    Rows with a heavy key meet it by broadcast and stay where they are; only the others are dealt out by key.
    """
    on = list(on)
    total = right.agg(F.sum(n)).first()[0] or 0
    heavy = F.col(n) > max(HEAVY_ROWS, total // HEAVY_SHARE)
    few = F.broadcast(right.where(heavy).drop(n))
    many = right.where(~heavy).drop(n)
    rest = left.join(F.broadcast(right.where(heavy).select(*on)), on, "left_anti")
    return left.join(few, on).unionByName(rest.join(many, on, "left"))
