"""Joins whose key may hold any share of the rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def join_by_count(rows: DataFrame, facts: DataFrame, keys: list[str], count: str = "c") -> DataFrame:
    """Inner join of ``rows`` with ``facts``, one stored row a key with the number of ``rows`` it has in
    ``count``. Keys of over one in 100,000 of the rows (and 10,000 at least) are fewer than 100,000
    whatever the data, so those facts are broadcast; no other key can fill a task."""
    total = facts.agg(F.sum(count)).first()[0] or 0
    limit = max(10_000, total // 100_000)
    hot = F.broadcast(facts.where(F.col(count) > limit))
    often = rows.join(hot, keys)
    rare = rows.join(F.broadcast(hot.select(*keys)), keys, "left_anti").join(facts.where(F.col(count) <= limit), keys)
    return often.unionByName(rare)
