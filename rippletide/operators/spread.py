"""Spread measures over activations (run, world, id, step, parent, o_final)."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rippletide.operators import diffusion
from rippletide.operators.graphs import InfluenceGraph


def weighed(o: Column, lam: float) -> Column:
    return F.when(o < 0, o * float(lam)).otherwise(o)


def spread(act: DataFrame) -> DataFrame:
    """(run, world, spread): activated nodes that are no seeds."""
    return act.groupBy("run", "world").agg(F.count(F.when(F.col("step") > 0, 1)).alias("spread"))


def opinion_spread(act: DataFrame, lam: float = 1.0) -> DataFrame:
    """(run, world, spread): sum of final opinions, negative ones times ``lam``, without the seeds."""
    return act.groupBy("run", "world").agg(F.sum(F.when(F.col("step") > 0, weighed(F.col("o_final"), lam)).otherwise(0.0)).alias("spread"))


def expected(per_world: DataFrame, worlds: int) -> DataFrame:
    """(run, spread, stderr): mean over worlds and its standard error."""
    return per_world.groupBy("run").agg((F.sum("spread") / worlds).alias("spread"), (F.coalesce(F.stddev_samp("spread"), F.lit(0.0)) / worlds**0.5).alias("stderr"))


def simulate(g: InfluenceGraph, seeds: DataFrame, worlds: int, model: str = "ic", seed: int = 1, mode: str = "xxhash", max_steps: int | None = None) -> DataFrame:
    """Activations under "ic", "lt" (opinion layer with interactions), or "oc" / "oc-ic" (the opinion
    layer without interactions over lt / ic; this model is inferred, its definition is not in the text)."""
    if model in ("ic", "oc-ic"):
        return diffusion.cascade_ic(g, seeds, worlds, seed, max_steps, mode, interaction=model == "ic")
    if model in ("lt", "oc"):
        return diffusion.cascade_lt(g, seeds, worlds, seed, max_steps, mode, interaction=model == "lt")
    raise ValueError(model)


def expected_spread(g: InfluenceGraph, seeds: DataFrame, worlds: int, objective: str = "count", lam: float = 1.0, **kw) -> DataFrame:
    act = simulate(g, seeds, worlds, **kw)
    return expected(spread(act) if objective == "count" else opinion_spread(act, lam), worlds)


def activation_probability(act: DataFrame, worlds: int) -> DataFrame:
    return act.groupBy("run", "id").agg((F.count(F.lit(1)) / worlds).alias("probability"))


def marginal_gain(g: InfluenceGraph, seeds: list[int], extra: list[int], worlds: int, **kw) -> DataFrame:
    """(id, gain) of each extra node over ``seeds``, on common worlds. Seeds themselves do not count as
    spread, so a gain may be negative by the one node that becomes a seed."""
    spark = g.nodes.sparkSession
    rows = [(-1, s) for s in seeds] + [(x, s) for x in extra for s in [*seeds, x]]
    res = expected_spread(g, spark.createDataFrame(rows, "run long, id long"), worlds, **kw)
    base = res.where("run = -1").select(F.col("spread").alias("base"))
    return res.where("run >= 0").join(F.broadcast(base), how="left").select(F.col("run").alias("id"), (F.col("spread") - F.coalesce("base", F.lit(0.0))).alias("gain"))


def exact_worlds(g: InfluenceGraph, limit: int = 16) -> tuple[DataFrame, int]:
    """(world, u, v) of all 2**m arc subsets with (world, weight) folded in as ``weight``."""
    arcs = sorted((r["u"], r["v"], r["p"], r["phi"]) for r in g.edges.limit(limit + 1).collect())
    if len(arcs) > limit:
        raise ValueError(f"more than {limit} arcs")
    spark = g.nodes.sparkSession
    table = spark.createDataFrame([(i, *a) for i, a in enumerate(arcs)], "i int, u long, v long, p double, phi double")
    worlds = spark.range(1 << len(arcs)).select(F.col("id").alias("world"))
    rows = worlds.join(F.broadcast(table)).withColumn("on", F.expr("(shiftright(world, i) & 1) = 1"))
    weight = rows.groupBy("world").agg(F.product(F.when(F.col("on"), F.col("p")).otherwise(1 - F.col("p"))).alias("weight"))
    return rows.where("on").join(weight, "world").select("world", "u", "v", "phi", "weight"), len(arcs)


def exact_spread(g: InfluenceGraph, opinion: bool = False, limit: int = 16) -> DataFrame:
    """(id, spread) of every node as the only seed, over all worlds. With ``opinion``, simultaneous
    activators average and signs enter by their expectation, which is exact for plain opinion spread."""
    kept, _ = exact_worlds(g, limit)
    kept = kept.cache()
    n = g.nodes.count()
    own = g.nodes.select(F.col("id").alias("v"), "o")
    weights = kept.select("world", "weight").distinct()
    active = weights.join(g.nodes.select(F.col("id").alias("seed"), "o")).select("world", "seed", F.col("seed").alias("id"), F.lit(0).alias("step"), F.col("o").alias("op"))
    front = active
    for t in range(1, n):
        ahead = front.select("world", "seed", F.col("id").alias("u"), "op").join(kept, ["world", "u"]).join(active.select("world", "seed", F.col("id").alias("v")), ["world", "seed", "v"], "left_anti")
        new = ahead.groupBy("world", "seed", "v").agg(F.avg((2 * F.col("phi") - 1) * F.col("op")).alias("turn")).join(own, "v")
        from rippletide.plans.storage import stored

        front = stored(new.select("world", "seed", F.col("v").alias("id"), F.lit(t).alias("step"), ((F.col("o") + F.col("turn")) / 2).alias("op")), "exact")
        if front.isEmpty():
            break
        active = active.union(front)
    value = F.col("op") if opinion else F.lit(1.0)
    sums = active.where("step > 0").join(weights, "world").groupBy(F.col("seed").alias("id")).agg(F.sum(F.col("weight") * value).alias("spread"))
    return g.nodes.select("id").join(sums, "id", "left").select("id", F.coalesce("spread", F.lit(0.0)).alias("spread"))


def subsets(spark: SparkSession, ids: list[int], k: int) -> DataFrame:
    """(run, id) of all k-subsets of a short list."""
    rows = [(r, i) for r, c in enumerate(combinations(sorted(ids), k)) for i in c]
    return spark.createDataFrame(rows, "run long, id long")
