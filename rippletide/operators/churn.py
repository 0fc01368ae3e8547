"""Customer churn: labels, balance, propagation to opinions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rippletide.functions.rng import u01
from rippletide.operators.graphs import InfluenceGraph
from rippletide.plans.storage import stored
from rippletide.sources.tables import table


def churn_labels(spark: SparkSession, sf_dir: str, cut: str = "2001-01-01") -> DataFrame:
    """(id, label): -1 for customers whose last order lies before ``cut`` (or who have none), else 1."""
    last = table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.max("o_orderdate").alias("last"))
    c = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("id"))
    return c.join(last, F.col("id") == F.col("o_custkey"), "left").select("id", F.when(F.col("last") >= F.lit(cut).cast("timestamp"), 1).otherwise(-1).alias("label"))


def balanced_sample(rows: DataFrame, label: str, seed: int = 1, mode: str = "xxhash") -> DataFrame:
    """As many rows of each label as the rarest has, by lowest draw. Ranks are taken in 64 hash ranges a
    label and offset by the ranges before, so no task ranks a whole label."""
    d = rows.withColumn("draw", u01("bal", seed, F.col("id"), mode=mode)).withColumn("slot", F.floor(F.col("draw") * 64).cast("int"))
    sizes = d.groupBy(label, "slot").agg(F.count(F.lit(1)).alias("c"))
    before = F.coalesce(F.sum("c").over(Window.partitionBy(label).orderBy("slot").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    least = sizes.groupBy(label).agg(F.sum("c").alias("c")).agg(F.min("c").alias("least"))
    base = sizes.select(label, "slot", before.alias("base"))
    ranked = d.withColumn("r", F.row_number().over(Window.partitionBy(label, "slot").orderBy("draw", "id"))).join(F.broadcast(base), [label, "slot"]).join(F.broadcast(least))
    return ranked.where(F.col("base") + F.col("r") <= F.col("least")).select(*rows.columns)


def propagate_labels(g: InfluenceGraph, labels: DataFrame, clamp: float = 0.5, tol: float = 1e-4, max_iter: int = 50, rounds: int | None = None) -> DataFrame:
    """(id, value): each round a node takes ``clamp`` of its own label and the rest of its in-neighbours'
    p-weighted mean (its own value where it has none), until no value moves by more than ``tol``; with
    ``rounds``, exactly that many."""
    own = stored(g.nodes.select("id").join(labels.select("id", F.col("label").cast("double").alias("label")), "id", "left").select("id", F.coalesce("label", F.lit(0.0)).alias("label")), "labels")
    state, edges = own.select("id", F.col("label").alias("value")), g.edges.select("u", "v", "p")
    for _ in range(rounds or max_iter):
        mean = edges.join(state.select(F.col("id").alias("u"), F.col("value").alias("x")), "u").groupBy(F.col("v").alias("id")).agg((F.sum(F.col("p") * F.col("x")) / F.sum("p")).alias("m"))
        new = own.join(state.withColumnRenamed("value", "old"), "id").join(mean, "id", "left").select("id", (clamp * F.col("label") + (1 - clamp) * F.coalesce("m", "old")).alias("value"), "old")
        new = stored(new, "values")
        if rounds is None and (new.agg(F.max(F.abs(F.col("value") - F.col("old")))).first()[0] or 0.0) <= tol:
            return new.select("id", "value")
        state = new.select("id", "value")
    return state
