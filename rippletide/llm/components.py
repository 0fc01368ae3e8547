"""Connected components by alternating large-star and small-star edge rewrites."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rippletide.llm.scratch import stored


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    low = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
    return both.where("b > a").join(low, "a").select(F.col("m").alias("a"), "b").where("a <> b").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    low = down.groupBy("a").agg(F.min("b").alias("m"))
    linked = down.join(low, "a").select(F.col("m").alias("a"), "b")
    return linked.union(low.select(F.col("m").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct()


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """``edges`` (a, b long) to rows (id, component), component the smallest id reachable, for every
    id on an edge. Each round is two aggregations and two joins, none of which gathers a group in
    one task; it stops when the edge set no longer changes (count and checksum), which takes about
    log(n) rounds. ``max_rounds`` guards against a defect, and reaching it raises."""
    def mark(e: DataFrame) -> tuple:
        return tuple(e.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("a", "b"))).first())

    now = stored(edges.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "cc")
    seen = mark(now)
    for _ in range(max_rounds):
        if seen[0] == 0:
            break
        now = stored(_small_star(_large_star(now)).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "cc")
        after = mark(now)
        if after == seen:
            break
        seen = after
    else:
        raise RuntimeError("components did not settle")
    return now.select(F.col("b").alias("id"), F.col("a").alias("component")).union(
        now.select(F.col("a").alias("id"), F.col("a").alias("component")).distinct()
    )
