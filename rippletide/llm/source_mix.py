"""Mixing sources to target weights by Sainte-Lague apportionment, in built-in expressions only.

Sources, by code point and null last, weigh ``weights`` in turn and share ``share`` of all words.
A target stops at ``max_repeat`` times its source's size; the excess goes to the others by weight
until none is above, which is one water level: target = least(cap, level * weight).

Blocks of ``block`` words go to sources by highest quotients target / (2 * blocks + 1). No loop over
blocks is needed: the common divisor that this amounts to lies within n / 2 blocks of the targets' own
sum (n sources), which leaves about two doubtful quotients a source; those are ranked. A source's blocks
are apportioned alike to its sections and a section's to its shards, by their sizes. A shard is a hash
range of documents of about ``shard_words`` words and a section one of ``SECTION`` shards, so no window
holds more than a shard's documents, a section's shards or a source's sections. Only the table of
sources, one row each, is ordered in one task.

Within a shard documents queue in seeded hash order and the quota is a range of that queue, read
again from its start for repeats: at most one document of a shard is taken in part.

Defined results: null text has size 0; rows with a null or repeated doc_id are documents of their own
(equal rows are interchangeable); a source of size 0 has target 0. Same input and seed, same result.
Columns of ``keep`` that are named like an output come out as ``in_<name>``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rippletide.llm.scratch import stored

WORD = r"[^\x20\x09-\x0D]+"
SECTION = 4096
OUT = ("doc_id", "size", "source_size", "target", "taken")


def targets(totals: DataFrame, weights: tuple[int, ...] = (5, 2, 1), share: float = 1.5, max_repeat: int = 2) -> DataFrame:
    """(source, source_size) to source, source_size, target. One row per source throughout."""
    order = Window.orderBy(F.col("source").isNull(), "source")
    turn = F.get(F.array(*[F.lit(float(w)) for w in weights]), (F.row_number().over(order) - 1) % len(weights))
    rows = totals.select("source", "source_size", turn.alias("w"), (F.col("source_size") * float(max_repeat)).alias("cap"))
    everything = Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    by_ratio = Window.orderBy(F.col("cap") / F.col("w"), F.col("source").isNull(), "source")
    before = by_ratio.rowsBetween(Window.unboundedPreceding, -1)
    after = by_ratio.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    level = (F.sum("source_size").over(everything) * share - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / F.sum("w").over(after)
    # By cap / weight, sources before the first that stays under its cap are full; its level holds for
    # it and for all after it.
    rows = rows.withColumn("ratio", F.col("cap") / F.col("w")).withColumn("level", level)
    rows = rows.withColumn("first", F.min(F.when(F.col("level") < F.col("ratio"), F.struct("ratio", "level"))).over(everything))
    open_ = F.coalesce(F.col("ratio") >= F.col("first.ratio"), F.lit(False))
    return rows.select("source", "source_size", F.when(open_, F.col("first.level") * F.col("w")).otherwise(F.col("cap")).alias("target"))


def apportioned(rows: DataFrame, claim: str, seats: str, within: list[str], tie: str, out: str) -> DataFrame:
    """``rows`` with ``out``: of the ``seats`` of each group, one to each of the highest quotients
    claim / (2 * got + 1), ties to the larger claim, then in order of ``tie`` (unique in a group). Claims
    of a group sum to its seats; so the seats of a row lie within claim * (1 +- n / (2 * seats)) +- 1/2."""
    group = Window.partitionBy(*within)
    lean = F.try_divide(F.count(F.lit(1)).over(group), 2 * F.col(seats))
    rows = rows.withColumn("_lean", F.coalesce(lean, F.lit(0.0)))
    low = F.greatest(F.lit(0), F.floor(F.col(claim) * (1 - F.col("_lean")) - 0.5)).cast("long")
    high = F.when(F.col(claim) > 0, F.ceil(F.col(claim) * (1 + F.col("_lean")) + 0.5)).otherwise(F.lit(0)).cast("long")
    rows = rows.withColumn("_low", F.when(F.col(seats) > 0, low).otherwise(F.lit(0)).cast("long"))
    rows = rows.withColumn("_spare", F.col(seats) - F.sum("_low").over(group))
    doubtful = rows.select(*within, F.col(tie).alias("_tie"), F.col(claim).alias("_claim"), "_spare", F.explode(F.sequence(F.col("_low"), F.greatest(high, F.col("_low")))).alias("_k"))
    queue = group.orderBy(F.desc(F.col("_claim") / (2 * F.col("_k") + 1)), F.desc("_claim"), "_tie")
    won = doubtful.withColumn("_place", F.row_number().over(queue)).where("_place <= _spare").groupBy(*within, "_tie").agg(F.count(F.lit(1)).alias("_more"))
    both = rows.withColumn("_tie", F.col(tie)).join(won, [*within, "_tie"], "left")
    return both.withColumn(out, F.col("_low") + F.coalesce("_more", F.lit(0))).drop("_lean", "_low", "_spare", "_tie", "_more")


def mix(docs: DataFrame, weights: tuple[int, ...] = (5, 2, 1), share: float = 1.5, max_repeat: int = 2, block: int = 8, shard_words: int = 50_000, seed: int = 11, text: str = "text", key: str = "doc_id", source: str = "source", keep: list[str] | None = None) -> DataFrame:
    """Per row: doc_id, size, source_size, target, taken, and the columns of ``keep``."""
    kept = [F.col(c).alias(f"keep_{c}") for c in keep or []]
    size = F.coalesce(F.regexp_count(F.col(text).cast("string"), F.lit(WORD)), F.lit(0)).cast("long")
    sized = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(source).cast("string").alias("source"), size.alias("size"), *kept)
    sized = sized.withColumn("draw", F.md5(F.concat_ws("|", F.lit(str(seed)), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))).cast("binary")))
    if not keep:
        sized = stored(sized, "sized")
    totals = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    plan = targets(totals, weights, share, max_repeat)
    whole = Window.partitionBy("all")
    plan = plan.withColumn("all", F.lit(1)).withColumn("sid", F.row_number().over(Window.orderBy(F.col("source").isNull(), "source")))
    plan = plan.withColumn("seats", F.round(F.sum("target").over(whole) / block).cast("long"))
    plan = plan.withColumn("claim", F.coalesce(F.try_divide(F.col("target") * F.col("seats"), F.sum("target").over(whole)), F.lit(0.0)))
    plan = apportioned(plan, "claim", "seats", ["all"], "sid", "blocks")
    plan = stored(plan.select("source", "source_size", "target", "blocks", "sid", F.greatest(F.lit(1), F.ceil(F.col("source_size") / shard_words)).alias("shards")), "targets")

    number = F.conv(F.substring("draw", 1, 15), 16, 10).cast("long")
    rows = sized.join(plan, sized["source"].eqNullSafe(plan["source"])).drop("source").withColumn("shard", F.pmod(number, F.col("shards"))).withColumn("section", F.floor(F.col("shard") / SECTION))
    shards = rows.groupBy("sid", "section", "shard").agg(F.sum("size").alias("shard_size"), F.first("source_size").alias("of"), F.first("blocks").alias("blocks"))
    part = lambda size: F.coalesce(F.try_divide(F.col("blocks") * F.col(size), F.col("of")), F.lit(0.0))
    sections = shards.groupBy("sid", "section").agg(F.sum("shard_size").alias("section_size"), F.first("of").alias("of"), F.first("blocks").alias("blocks")).withColumn("claim", part("section_size"))
    sections = apportioned(sections, "claim", "blocks", ["sid"], "section", "section_blocks").select("sid", "section", F.col("section_size").alias("of"), F.col("section_blocks").alias("blocks"))
    quota = shards.select("sid", "section", "shard", "shard_size").join(sections, ["sid", "section"]).withColumn("claim", part("shard_size"))
    quota = apportioned(quota, "claim", "blocks", ["sid", "section"], "shard", "shard_blocks").select("sid", "shard", (F.col("shard_blocks") * block).alias("quota"), "shard_size")

    placed = rows.join(quota, ["sid", "shard"])
    queue = Window.partitionBy("sid", "shard").orderBy("draw", "doc_id", "size").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    placed = placed.withColumn("end", F.sum("size").over(queue))
    begin = F.col("end") - F.col("size")
    taken = F.lit(0).cast("long")
    for k in range(max_repeat):
        left = F.col("quota") - k * F.col("shard_size")
        taken = taken + F.greatest(F.lit(0), F.least(F.col("end"), left) - begin)
    return placed.select("doc_id", "size", "source_size", "target", taken.alias("taken"), *[F.col(f"keep_{c}").alias(f"in_{c}" if c in OUT else c) for c in keep or []])
