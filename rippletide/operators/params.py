"""Assignment of propagation, threshold, opinion and interaction parameters."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rippletide.functions.rng import normal, u01
from rippletide.operators.graphs import InfluenceGraph


def assign_ic(g: InfluenceGraph, p: float = 0.1) -> InfluenceGraph:
    return g.with_p(F.lit(float(p)))


def _indegree(edges: DataFrame) -> DataFrame:
    return edges.groupBy("v").agg(F.count(F.lit(1)).alias("indeg"))


def assign_wc(g: InfluenceGraph) -> InfluenceGraph:
    """p = 1 / in-degree of the head."""
    edges = g.edges.join(_indegree(g.edges), "v").select("u", "v", (1.0 / F.col("indeg")).alias("p"), "w", "phi")
    return replace(g, edges=edges)


def assign_lt(g: InfluenceGraph, seed: int = 1, mode: str = "xxhash") -> InfluenceGraph:
    """w = 1 / in-degree of the head; threshold uniform per node."""
    edges = g.edges.join(_indegree(g.edges), "v").select("u", "v", "p", (1.0 / F.col("indeg")).alias("w"), "phi")
    return InfluenceGraph(g.nodes.withColumn("theta", u01("theta", seed, F.col("id"), mode=mode)), edges)


def opinions_uniform(g: InfluenceGraph, seed: int = 1, mode: str = "xxhash") -> InfluenceGraph:
    return replace(g, nodes=g.nodes.withColumn("o", 2 * u01("o", seed, F.col("id"), mode=mode) - 1))


def opinions_normal(g: InfluenceGraph, seed: int = 1, bound: str = "clip", mode: str = "xxhash") -> InfluenceGraph:
    """Standard normal opinions; ``bound`` clips them to [-1, 1], divides by the largest magnitude, or
    leaves them."""
    nodes = g.nodes.withColumn("o", normal("n", seed, F.col("id"), mode=mode))
    if bound == "clip":
        nodes = nodes.withColumn("o", F.greatest(F.lit(-1.0), F.least(F.lit(1.0), "o")))
    elif bound == "rescale":
        most = nodes.agg(F.max(F.abs("o")).alias("most"))
        nodes = nodes.join(F.broadcast(most)).withColumn("o", F.col("o") / F.greatest("most", F.lit(1e-300))).drop("most")
    elif bound != "none":
        raise ValueError(bound)
    return replace(g, nodes=nodes)


def interactions_uniform(g: InfluenceGraph, seed: int = 1, mode: str = "xxhash") -> InfluenceGraph:
    return replace(g, edges=g.edges.withColumn("phi", u01("phi", seed, F.col("u"), F.col("v"), mode=mode)))
