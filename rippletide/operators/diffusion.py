"""Diffusion in many worlds at once.

State is one row per (run, world, node); ``run`` tells seed sets apart that share the worlds, so that
marginal gains compare the same coins. Coins are hashes of (world, arc). Each step is one join of the
newest nodes with the arcs and one aggregation; it is stored, and the loop ends with an empty step, which
comes after at most as many steps as there are nodes. ``max_steps`` asks for an earlier end."""

from __future__ import annotations

from collections.abc import Iterable
from itertools import count

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rippletide.functions.rng import u01
from rippletide.operators.graphs import InfluenceGraph
from rippletide.plans.storage import small, stored, stored_with_count

ACT = ["run", "world", "id", "step", "parent", "o_final"]


def steps_to(max_steps: int | None) -> Iterable[int]:
    return count(1) if max_steps is None else range(1, max_steps + 1)


def joined(active: DataFrame, front: DataFrame, t: int) -> DataFrame:
    """All activations so far, stored anew now and then so that the plan of a deep cascade stays short."""
    both = active.union(front)
    return both if t % 16 else stored(both, "active")


def starts(g: InfluenceGraph, seeds: DataFrame, worlds: int) -> DataFrame:
    """Seeds (id, and optionally run) in every world, active at step 0 with their own opinion."""
    run = F.col("run").cast("long") if "run" in seeds.columns else F.lit(0).cast("long")
    rows = seeds.select(run.alias("run"), F.col("id").cast("long").alias("id")).distinct().join(g.nodes.select("id", "o"), "id")
    return rows.select("run", F.explode(F.sequence(F.lit(0), F.lit(worlds - 1))).alias("world"), "id", F.lit(0).alias("step"), F.lit(None).cast("long").alias("parent"), F.col("o").alias("o_final"))


def _turned(world: Column, phi: Column, seed: int, mode: str, interaction: bool) -> Column:
    """+1 with probability phi, else -1; always +1 without interactions."""
    if not interaction:
        return F.lit(1.0)
    return F.when(u01("sign", seed, world, F.col("u"), F.col("v"), mode=mode) < phi, 1.0).otherwise(-1.0)


def cascade_ic(g: InfluenceGraph, seeds: DataFrame, worlds: int, seed: int = 1, max_steps: int | None = None, mode: str = "xxhash", interaction: bool = True, plain: bool = False) -> DataFrame:
    """Independent cascade with the opinion layer. Each node gets one try per out-arc in the step after
    its activation; of several successful activators one is drawn per world by hash, and the new opinion
    is the mean of the own one and the activator's, turned round with probability 1 - phi. Opinions never
    change who activates whom: with ``plain``, ``o_plain`` is the opinion that the same run gives without
    interactions."""
    kinds = ["o_final", "o_plain"] if plain else ["o_final"]
    begun = starts(g, seeds, worlds)
    active, n = stored_with_count(begun.withColumn("o_plain", F.col("o_final")) if plain else begun, "active")
    front = active
    own = g.nodes.select(F.col("id").alias("v"), "o")
    for t in steps_to(max_steps):
        if not n:
            break
        edges = g.arcs_from(front.select(F.col("id").alias("u")), n).select("u", "v", "p", "phi")
        tried = edges.join(small(front.select("run", "world", F.col("id").alias("u"), *kinds), n), "u").where(u01("ic", seed, F.col("world"), F.col("u"), F.col("v"), mode=mode) < F.col("p"))
        fresh = tried.join(active.select("run", "world", F.col("id").alias("v")), ["run", "world", "v"], "left_anti")
        pick = F.struct(u01("tie", seed, F.col("world"), F.col("u"), F.col("v"), mode=mode).alias("h"), F.col("u").alias("u"), (F.col("o_final") * _turned(F.col("world"), F.col("phi"), seed, mode, interaction)).alias("o_final"), *kinds[1:])
        won = fresh.groupBy("run", "world", "v").agg(F.min(pick).alias("w")).join(own, "v")
        new = won.select("run", "world", F.col("v").alias("id"), F.lit(t).alias("step"), F.col("w.u").alias("parent"), *[((F.col("o") + F.col(f"w.{k}")) / 2).alias(k) for k in kinds])
        front, n = stored_with_count(new, "front")
        active = joined(active, front, t)
    return active.select(*ACT, *kinds[1:])


def cascade_lt(g: InfluenceGraph, seeds: DataFrame, worlds: int, seed: int = 1, max_steps: int | None = None, mode: str = "xxhash", interaction: bool = True, thresholds: str = "world") -> DataFrame:
    """Linear threshold: a node fires when the weights of its active in-neighbours reach its threshold
    (drawn per world, or the node's ``theta``). Its opinion is the mean of its own and the average
    turned opinion of all in-neighbours active before. Pressure and opinion sums are kept per node, so a
    step reads the arcs of the newest nodes only."""
    active, n = stored_with_count(starts(g, seeds, worlds), "active")
    front, edges = active, g.edges.select("u", "v", "w", "phi")
    own = g.nodes.select(F.col("id").alias("v"), "o", "theta")
    held = None
    for t in steps_to(max_steps):
        if not n:
            break
        push = edges.join(small(front.select("run", "world", F.col("id").alias("u"), "o_final"), n), "u").join(active.select("run", "world", F.col("id").alias("v")), ["run", "world", "v"], "left_anti")
        turned = F.col("o_final") * _turned(F.col("world"), F.col("phi"), seed, mode, interaction)
        add = push.select("run", "world", "v", "w", turned.alias("turn"), F.lit(1).cast("long").alias("c"), F.col("u").alias("parent"))
        both = add if held is None else held.unionByName(add)
        sums = both.groupBy("run", "world", "v").agg(F.sum("w").alias("w"), F.sum("turn").alias("turn"), F.sum("c").alias("c"), F.min("parent").alias("parent"))
        limit = u01("theta", seed, F.col("world"), F.col("v"), mode=mode) if thresholds == "world" else F.col("theta")
        judged, _ = stored_with_count(sums.join(own, "v").withColumn("fires", F.col("w") >= limit), "pressure")
        new = judged.where("fires").select("run", "world", F.col("v").alias("id"), F.lit(t).alias("step"), "parent", ((F.col("o") + F.col("turn") / F.col("c")) / 2).alias("o_final"))
        held = judged.where("not fires").select("run", "world", "v", "w", "turn", "c", "parent")
        front, n = stored_with_count(new, "front")
        active = joined(active, front, t)
    return active.select(*ACT)


def live_edges(g: InfluenceGraph, worlds: int, seed: int = 1, mode: str = "xxhash") -> DataFrame:
    """(world, u, v): in each world every node keeps at most one in-arc, each with probability w. The
    arcs' running weights are one window per head, computed once for all worlds."""
    upto = F.sum("w").over(Window.partitionBy("v").orderBy("u").rowsBetween(Window.unboundedPreceding, 0))
    spans = g.edges.select("u", "v", "w", upto.alias("high"))
    rows = spans.select("u", "v", (F.col("high") - F.col("w")).alias("low"), "high", F.explode(F.sequence(F.lit(0), F.lit(worlds - 1))).alias("world"))
    draw = u01("live", seed, F.col("world"), F.col("v"), mode=mode)
    return rows.where((draw >= F.col("low")) & (draw < F.col("high"))).select("world", "u", "v")


def sample_worlds(g: InfluenceGraph, worlds: int, seed: int = 1, mode: str = "xxhash") -> DataFrame:
    """(world, u, v): independent-cascade worlds, each arc kept with probability p."""
    rows = g.edges.select("u", "v", "p", F.explode(F.sequence(F.lit(0), F.lit(worlds - 1))).alias("world"))
    return rows.where(u01("ic", seed, F.col("world"), F.col("u"), F.col("v"), mode=mode) < F.col("p")).select("world", "u", "v")


def cascade_worlds(g: InfluenceGraph, seeds: DataFrame, kept: DataFrame, worlds: int, max_steps: int | None = None) -> DataFrame:
    """(run, world, id, step): what the seeds reach along the kept arcs (world, u, v)."""
    active, n = stored_with_count(starts(g, seeds, worlds).select("run", "world", "id", "step"), "active")
    front = active
    for t in steps_to(max_steps):
        if not n:
            break
        ahead = kept.join(small(front.select("run", "world", F.col("id").alias("u")), n), ["world", "u"]).select("run", "world", F.col("v").alias("id")).distinct()
        front, n = stored_with_count(ahead.join(active, ["run", "world", "id"], "left_anti").select("run", "world", "id", F.lit(t).alias("step")), "front")
        active = joined(active, front, t)
    return active


def reach_bits(g: InfluenceGraph, seeds: DataFrame, blocks: int = 1, seed: int = 1, max_steps: int | None = None, mode: str = "xxhash") -> DataFrame:
    """(run, block, id, bits): 64 independent-cascade worlds in one integer; bit b of block k is world
    64 * k + b, with the same coins as the row-wise cascade. Arc masks are computed once."""
    coins = F.lit(0).cast("long")
    world = lambda b: F.col("block") * 64 + b
    for b in range(64):
        bit = F.lit((1 << b) if b < 63 else -(1 << 63)).cast("long")
        coins = coins.bitwiseOR(F.when(u01("ic", seed, world(b), F.col("u"), F.col("v"), mode=mode) < F.col("p"), bit).otherwise(F.lit(0).cast("long")))
    arcs = g.edges.select("u", "v", "p", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("block"))
    masks, _ = stored_with_count(arcs.select("block", "u", "v", coins.alias("mask")).where("mask <> 0"), "masks")
    run = F.col("run").cast("long") if "run" in seeds.columns else F.lit(0).cast("long")
    state, n = stored_with_count(seeds.select(run.alias("run"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("block"), F.col("id").cast("long").alias("id"), F.lit(-1).cast("long").alias("bits"), F.lit(-1).cast("long").alias("new")), "bits")
    for _ in steps_to(max_steps):
        front = state.where("new <> 0").select("run", "block", F.col("id").alias("u"), "new")
        ahead = masks.join(front, ["block", "u"]).select("run", "block", F.col("v").alias("id"), F.col("new").bitwiseAND(F.col("mask")).alias("got")).where("got <> 0")
        got = ahead.groupBy("run", "block", "id").agg(F.bit_or("got").alias("got"))
        both = state.select("run", "block", "id", "bits").join(got, ["run", "block", "id"], "full")
        zero = F.lit(0).cast("long")
        old = F.coalesce("bits", zero)
        new = F.coalesce("got", zero).bitwiseAND(F.bitwise_not(old))
        state, n = stored_with_count(both.select("run", "block", "id", old.bitwiseOR(new).alias("bits"), new.alias("new")), "bits")
        if state.where("new <> 0").isEmpty():
            break
    return state.select("run", "block", "id", "bits")
