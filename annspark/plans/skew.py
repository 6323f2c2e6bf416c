"""Joins on keys of which a few may hold a large share of the rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: A key is hot if it has more than one row in so many; so fewer keys than this can be hot.
HOT_SHARE = 1000


def join_hot_apart(left: DataFrame, right: DataFrame, key: str, rows: str) -> DataFrame:
    """Inner join of ``left`` with ``right``, which has one row for each key and counts ``left``'s rows in ``rows``.

    Hot keys are fewer than HOT_SHARE by definition, so their side is broadcast
    and their rows stay where they are; all other keys are shuffled.
    """
    total = right.agg(F.sum(rows)).first()[0] or 0
    hot = right.where(F.col(rows) > total // HOT_SHARE + 1).drop(rows)
    cold = right.where(F.col(rows) <= total // HOT_SHARE + 1).drop(rows)
    first = left.join(F.broadcast(hot), key)
    rest = left.join(F.broadcast(hot.select(key)), key, "left_anti").join(cold, key)
    return first.unionByName(rest)
