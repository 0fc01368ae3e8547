"""Error measures of the scores and checks of the spread function's properties."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rippletide.operators.graphs import InfluenceGraph
from rippletide.operators.scores import simple_paths
from rippletide.plans.storage import stored


def path_mass(g: InfluenceGraph, max_len: int) -> DataFrame:
    """(u, v, mass, paths): sum over simple paths of up to ``max_len`` arcs of the product of p."""
    return simple_paths(g, max_len).groupBy(F.col("src").alias("u"), F.col("dst").alias("v")).agg(F.sum("x").alias("mass"), F.count(F.lit(1)).alias("paths"))


def path_pair_mass(g: InfluenceGraph, max_len: int) -> DataFrame:
    """(u, v, arcs, product): second-order mass over unordered pairs of distinct paths between two nodes;
    ``arcs`` multiplies p over the union of their arcs, ``product`` over both paths."""
    edges = g.edges.select("u", "v", "p")
    steps = F.transform(F.sequence(F.lit(1), F.size("path") - 1), lambda i: F.struct(F.element_at("path", i).alias("u"), F.element_at("path", i + 1).alias("v")))
    paths = simple_paths(g, max_len).select("src", "dst", "path", "x", steps.alias("steps"))
    a = paths.select("src", "dst", F.col("path").alias("pa"), F.col("x").alias("xa"), F.col("steps").alias("sa"))
    b = paths.select("src", "dst", F.col("path").alias("pb"), F.col("x").alias("xb"), F.col("steps").alias("sb"))
    pairs = a.join(b, ["src", "dst"]).where(F.array_join(F.transform("pa", lambda i: i.cast("string")), ",") < F.array_join(F.transform("pb", lambda i: i.cast("string")), ","))
    shared = pairs.withColumn("key", F.struct("pa", "pb")).select("src", "dst", "key", "xa", "xb", F.explode_outer(F.array_intersect("sa", "sb")).alias("s"))
    joint = shared.join(edges, (F.col("s.u") == F.col("u")) & (F.col("s.v") == F.col("v")), "left").groupBy("src", "dst", "key").agg(F.max("xa").alias("xa"), F.max("xb").alias("xb"), F.product(F.coalesce("p", F.lit(1.0))).alias("common"))
    return joint.groupBy(F.col("src").alias("u"), F.col("dst").alias("v")).agg(F.sum(F.col("xa") * F.col("xb") / F.col("common")).alias("arcs"), F.sum(F.col("xa") * F.col("xb")).alias("product"))


def contribution(g: InfluenceGraph, max_len: int) -> DataFrame:
    """(u, v, summed, united): what v adds to the score of u by the sum and by the union of its paths."""
    return simple_paths(g, max_len).groupBy(F.col("src").alias("u"), F.col("dst").alias("v")).agg(F.sum("x").alias("summed"), (1 - F.product(1 - F.col("x"))).alias("united"))


def dag_bounds(g: InfluenceGraph, max_len: int, p: float) -> DataFrame:
    """Per start: size of the first-order error bounds on a DAG with uniform p: of the union score
    against the truth, of the walk score against the union score, and of both together."""
    mass, pairs = path_mass(g, max_len), path_pair_mass(g, max_len)
    first = mass.groupBy("u").agg(F.sum("mass").alias("mass"))
    second = pairs.groupBy("u").agg(F.sum("product").alias("product"))
    rows = first.join(second, "u", "left")
    return rows.select(F.col("u").alias("id"), F.abs((p - 1) * F.col("mass")).alias("union_bound"), F.coalesce("product", F.lit(0.0)).alias("walk_bound"), F.abs((2 * p - 1) * F.col("mass")).alias("total_bound"))


def cycle_error(g: InfluenceGraph, max_len: int) -> DataFrame:
    """(id, error): for each node the cycles of up to ``max_len`` arcs through it, each by its product of p
    over its number of arcs."""
    paths = simple_paths(g, max_len - 1).select("src", "dst", "x", "length")
    back = paths.join(g.edges.select("u", "v", "p"), (F.col("dst") == F.col("u")) & (F.col("src") == F.col("v")))
    return back.groupBy(F.col("src").alias("id")).agg(F.sum(F.col("x") * F.col("p") / (F.col("length") + 1)).alias("error"))


def order_condition(scores: DataFrame, exact: DataFrame) -> DataFrame:
    """(u, v, holds, kept) for pairs with exact(u) > exact(v): whether the relative error of v stays within
    that of u (the sufficient condition) and whether the score keeps the order. Small inputs: all
    ordered pairs are made."""
    rows = exact.select("id", F.col("spread").alias("t")).join(scores.select("id", F.col("score").alias("s")), "id").withColumn("e", F.col("s") - F.col("t"))
    a, b = rows.select(*[F.col(c).alias(f"{c}u") for c in rows.columns]), rows.select(*[F.col(c).alias(f"{c}v") for c in rows.columns])
    pairs = a.join(b, F.col("tu") > F.col("tv"))
    return pairs.select(F.col("idu").alias("u"), F.col("idv").alias("v"), (F.col("ev") - F.col("eu") < F.col("tu") - F.col("tv")).alias("holds"), (F.col("su") > F.col("sv")).alias("kept"))


def expected_path_mass(edges: DataFrame, p: float, max_len: int) -> DataFrame:
    """(i, mass, cycle_mass, critical): growth of the path mass with length i when every node has as many
    successors as the tails of ``edges`` (u) on average (eta), the same over i for cycles, and eta * p, whose
    passing 1 makes it diverge."""
    eta = edges.agg((F.count("u") / F.count_distinct("u")).alias("eta")).where("eta is not null")
    rows = eta.select("eta", F.explode(F.sequence(F.lit(1).cast("long"), F.lit(max_len).cast("long"))).alias("i"))
    mass = F.pow("eta", F.col("i") - 1) * F.pow(F.lit(float(p)), "i")
    return rows.select("i", mass.alias("mass"), (mass / F.col("i")).alias("cycle_mass"), (F.col("eta") * p).alias("critical"))


def repeated_paths(counts: DataFrame, p: float, length: int) -> DataFrame:
    """(t, united, summed) for each number of paths in ``counts`` (t): t equal paths of ``length`` arcs, united
    or summed."""
    one = float(p) ** length
    return counts.select("t").distinct().select("t", (1 - F.pow(F.lit(1 - one), F.col("t"))).alias("united"), (F.col("t") * one).alias("summed"))


def violation_window(counts: DataFrame, p: float) -> DataFrame:
    """(t1, t2, gap) for each two numbers of paths t1 > t2 in ``counts`` (t): how much longer t1 paths may be
    than t2 and still sum to more, log base 1/p of t1 / t2."""
    t = counts.select("t").distinct()
    rows = t.withColumnRenamed("t", "t1").join(t.withColumnRenamed("t", "t2"), F.col("t1") > F.col("t2"))
    return rows.select("t1", "t2", (F.log(F.col("t1") / F.col("t2")) / -F.log(F.lit(float(p)))).alias("gap"))


def decomposition(act: DataFrame, a: int, b: int, both: int) -> DataFrame:
    """Per world, from runs of A, B and A with B on common worlds: spread of the union and its parts
    reached by A, and by B only."""
    sets = {x: act.where(F.col("run") == r).select("world", "id") for x, r in (("a", a), ("b", b), ("ab", both))}
    count = lambda df, name: df.groupBy("world").agg(F.count(F.lit(1)).alias(name))
    rest = sets["b"].join(sets["a"], ["world", "id"], "left_anti")
    rows = count(sets["ab"], "n_union").join(count(sets["a"], "n_a"), "world", "left").join(count(rest, "n_rest"), "world", "left")
    return rows.select("world", "n_union", F.coalesce("n_a", F.lit(0)).alias("n_a"), F.coalesce("n_rest", F.lit(0)).alias("n_rest"))


def rank_agreement(left: DataFrame, right: DataFrame, k: int) -> DataFrame:
    """Concordant and discordant pairs, Kendall's tau-a, and overlap of the k best, of two scorings
    (id, score) of a small node set."""
    rows = stored(left.select("id", F.round("score", 9).alias("a")).join(right.select("id", F.round("score", 9).alias("b")), "id"), "ranks")
    x, y = rows.toDF("i", "a1", "b1"), rows.toDF("j", "a2", "b2")
    sign = F.signum(F.col("a1") - F.col("a2")) * F.signum(F.col("b1") - F.col("b2"))
    pairs = x.join(y, F.col("i") < F.col("j")).agg(F.sum((sign > 0).cast("long")).alias("concordant"), F.sum((sign < 0).cast("long")).alias("discordant"), F.avg(sign).alias("tau"))
    top = lambda c: rows.orderBy(F.desc(c), "id").limit(k).select("id")
    common = top("a").join(top("b"), "id").agg((F.count(F.lit(1)) / k).alias("overlap"))
    return pairs.join(common)


def violations(g: InfluenceGraph, ids: list[int], lam: float = 1.0) -> DataFrame:
    """(kind, n) over all sets of a short list of nodes: how often adding a node lowers the opinion spread,
    and how often a node gains more on top of a set than on a part of it. Sets are bit masks; one world."""
    from rippletide.operators import spread

    if len(ids) > 10:
        raise ValueError("for at most 10 nodes")
    spark = g.nodes.sparkSession
    rows = [(m, x) for m in range(1 << len(ids)) for i, x in enumerate(ids) if m >> i & 1]
    value = spread.expected_spread(g, spark.createDataFrame(rows, "run long, id long"), 1, objective="opinion", lam=lam)
    masks = stored(spark.range(1 << len(ids)).select(F.col("id").alias("m")).join(value.select(F.col("run").alias("m"), "spread"), "m", "left").select("m", F.coalesce("spread", F.lit(0.0)).alias("v")), "masks")
    bit = F.explode(F.array(*[F.lit(1 << i) for i in range(len(ids))])).alias("bit")
    steps = masks.select("m", "v", bit).where(F.col("m").bitwiseAND(F.col("bit")) == 0).withColumn("more", F.col("m") + F.col("bit"))
    gains = stored(steps.join(masks.select(F.col("m").alias("more"), F.col("v").alias("w")), "more").select("m", "bit", F.round(F.col("w") - F.col("v"), 9).alias("gain")), "gains")
    part = gains.select(F.col("m").alias("part"), "bit", F.col("gain").alias("less"))
    rises = gains.join(part, "bit").where((F.col("part").bitwiseAND(F.col("m")) == F.col("part")) & (F.col("part") != F.col("m")) & (F.round(F.col("gain") - F.col("less"), 9) > 0))
    count = lambda df, name: df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("kind"), "n")
    return count(gains.where("gain < 0"), "monotone").union(count(rises, "submodular"))


def submodularity(spark: SparkSession, g: InfluenceGraph, orders: list[int], lam: float = 1.0) -> DataFrame:
    """(size, spread): opinion spread as the seeds in ``orders`` are added one by one in one world."""
    from rippletide.operators import spread

    rows = [(n, s) for n in range(1, len(orders) + 1) for s in orders[:n]]
    res = spread.expected_spread(g, spark.createDataFrame(rows, "run long, id long"), 1, objective="opinion", lam=lam)
    return res.select(F.col("run").alias("size"), "spread")
