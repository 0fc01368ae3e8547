"""Node scores that stand for the expected spread of a single seed.

Every round joins the arcs, laid out by head, with the previous round's node state and sums by tail:
one narrow state exchange and one exchange of partial sums; the arcs themselves stay put."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rippletide.operators.graphs import InfluenceGraph
from rippletide.plans.storage import stored

#: Rounds that stay in one lazy plan; longer recursions store their state in between.
LAZY_ROUNDS = 4


def _next_walk(edges: DataFrame, state: DataFrame, keys: list[str]) -> DataFrame:
    step = edges.join(state.withColumnRenamed("id", "v"), ["v", *keys], "left")
    return step.groupBy(*keys, F.col("u").alias("id")).agg(F.sum(F.col("p") * (1 + F.coalesce("score", F.lit(0.0)))).alias("score"))


def walk_score(g: InfluenceGraph, max_len: int = 3) -> DataFrame:
    """(id, score): probability-weighted count of walks of up to ``max_len`` arcs from each node."""
    edges, state = g.edges.select("u", "v", "p"), None
    for i in range(max_len):
        if state is None:
            state = edges.groupBy(F.col("u").alias("id")).agg(F.sum("p").alias("score"))
        else:
            state = _next_walk(edges, stored(state, "score") if i % LAZY_ROUNDS == 0 else state, [])
    return g.nodes.select("id").join(state, "id", "left").select("id", F.coalesce("score", F.lit(0.0)).alias("score"))


def walk_score_profile(g: InfluenceGraph, max_len: int) -> DataFrame:
    """(id, l, score) for every l up to ``max_len``, in one pass of the rounds."""
    edges = g.edges.select("u", "v", "p")
    state, out = None, None
    for i in range(1, max_len + 1):
        state = edges.groupBy(F.col("u").alias("id")).agg(F.sum("p").alias("score")) if state is None else _next_walk(edges, state, [])
        state = stored(state, "score")
        one = g.nodes.select("id").join(state, "id", "left").select("id", F.lit(i).alias("l"), F.coalesce("score", F.lit(0.0)).alias("score"))
        out = one if out is None else out.union(one)
    return out


def opinion_walk_score(g: InfluenceGraph, max_len: int = 3) -> DataFrame:
    """(id, score): expected opinion gathered over walks of up to ``max_len`` arcs. Three sums a length
    travel together: end opinions, interaction products, and the carried opinions of the nodes on the
    way; a node adds its own opinion times its interaction product to what it carries."""
    edges = g.edges.select("u", "v", "p", "phi")
    own = g.nodes.select("id", "o")
    state = own.select("id", F.col("o").alias("ends"), F.lit(1.0).alias("alpha"), F.lit(0.0).alias("carry"), F.lit(0.0).alias("score"))
    for i in range(max_len):
        if i and i % LAZY_ROUNDS == 0:
            state = stored(state, "score")
        sums = (
            edges.join(state.select(F.col("id").alias("v"), "ends", "alpha", "carry"), "v")
            .groupBy(F.col("u").alias("id"))
            .agg(F.sum(F.col("p") * F.col("ends")).alias("ends"), F.sum(F.col("p") * F.col("alpha") * (F.col("phi") - 0.5)).alias("alpha"), F.sum(F.col("p") * F.col("carry")).alias("carry"))
        )
        zero = lambda c: F.coalesce(c, F.lit(0.0)).alias(c)
        joined = own.join(state.select("id", F.col("score").alias("before")), "id").join(sums, "id", "left").select("id", "o", "before", zero("ends"), zero("alpha"), zero("carry"))
        joined = joined.withColumn("turn", F.col("o") * F.col("alpha")).withColumn("carry", F.col("carry") + F.col("turn"))
        state = joined.select("id", "ends", "alpha", "carry", (F.col("before") + (F.col("ends") + F.col("carry") + F.col("turn")) / 2).alias("score"))
    return state.select("id", "score")


def assign_score(g: InfluenceGraph, max_len: int = 3, opinion: bool = False) -> DataFrame:
    return opinion_walk_score(g, max_len) if opinion else walk_score(g, max_len)


def _matrix_powers(g: InfluenceGraph, max_len: int, union: bool, max_cells: int) -> list[DataFrame]:
    base = g.edges.select(F.col("u").alias("k"), F.col("v").alias("j"), "p")
    power, out = g.edges.select(F.col("u").alias("i"), F.col("v").alias("j"), F.col("p").alias("x")).where("i <> j" if union else "true"), []
    for step in range(max_len):
        if step:
            value = (1 - F.product(1 - F.col("x") * F.col("p"))) if union else F.sum(F.col("x") * F.col("p"))
            left = power.select("i", F.col("j").alias("k"), "x")
            power = left.join(base, "k").groupBy("i", "j").agg(value.alias("x"))
            if union:
                power = power.where("i <> j")
        power = stored(power, "power")
        cells = power.count()
        if cells > max_cells:
            raise ValueError(f"{cells} cells: the quadratic score is a reference for small graphs")
        out.append(power)
    return out


def union_walk_score(g: InfluenceGraph, max_len: int = 3, max_cells: int = 50_000_000) -> DataFrame:
    """(id, score): as the walk score, but several walks between two nodes combine as independent events
    and walks through the start are dropped. Quadratic state: a reference method."""
    total = None
    for power in _matrix_powers(g, max_len, True, max_cells):
        one = power.groupBy(F.col("i").alias("id")).agg(F.sum("x").alias("s"))
        total = one if total is None else total.union(one)
    sums = total.groupBy("id").agg(F.sum("s").alias("score"))
    return g.nodes.select("id").join(sums, "id", "left").select("id", F.coalesce("score", F.lit(0.0)).alias("score"))


def walk_counts(g: InfluenceGraph, max_len: int = 3, max_cells: int = 50_000_000) -> DataFrame:
    """(u, v, walks): walks of up to ``max_len`` arcs between each pair."""
    total = None
    for power in _matrix_powers(g.with_p(F.lit(1.0)), max_len, False, max_cells):
        total = power if total is None else total.union(power)
    return total.groupBy(F.col("i").alias("u"), F.col("j").alias("v")).agg(F.sum("x").cast("long").alias("walks"))


def simple_paths(g: InfluenceGraph, max_len: int, prune: float = 0.0, starts: DataFrame | None = None) -> DataFrame:
    """(src, dst, path, x, length): simple paths of up to ``max_len`` arcs whose product of p is at
    least ``prune``. Exponential in ``max_len``: for small graphs, checks and pruned searches."""
    edges = g.edges.select("u", "v", "p")
    first = edges if starts is None else edges.join(starts.select(F.col("id").alias("u")).distinct(), "u", "left_semi")
    step = first.where((F.col("u") != F.col("v")) & (F.col("p") >= prune)).select(F.col("u").alias("src"), F.col("v").alias("dst"), F.array("u", "v").alias("path"), F.col("p").alias("x"), F.lit(1).alias("length"))
    step = stored(step, "paths")
    out = step
    for n in range(2, max_len + 1):
        grown = step.join(edges, F.col("dst") == F.col("u")).where(~F.array_contains("path", F.col("v")) & (F.col("x") * F.col("p") >= prune))
        step = stored(grown.select("src", F.col("v").alias("dst"), F.concat("path", F.array("v")).alias("path"), (F.col("x") * F.col("p")).alias("x"), F.lit(n).alias("length")), "paths")
        if step.isEmpty():
            break
        out = out.union(step)
    return out


def simple_path_score(g: InfluenceGraph, max_len: int = 3, combine: str = "sum") -> DataFrame:
    """Scores from simple paths only, by sum or (per pair) by union of their products."""
    per_pair = F.sum("x") if combine == "sum" else 1 - F.product(1 - F.col("x"))
    pairs = simple_paths(g, max_len).groupBy("src", "dst").agg(per_pair.alias("x"))
    sums = pairs.groupBy(F.col("src").alias("id")).agg(F.sum("x").alias("score"))
    return g.nodes.select("id").join(sums, "id", "left").select("id", F.coalesce("score", F.lit(0.0)).alias("score"))


def opinion_path_score(g: InfluenceGraph, max_len: int = 3, lam: float = 1.0) -> DataFrame:
    """Expected final opinion at the end of every walk, negative ones times ``lam``; walks are kept one
    by one, since the penalty is not linear. At lam = 1 it equals the opinion walk score."""
    edges = g.edges.select("u", "v", "p", "phi")
    own = g.nodes.select(F.col("id").alias("v"), "o")
    step = g.nodes.select(F.col("id").alias("src"), F.col("id").alias("at"), F.lit(1.0).alias("x"), F.col("o").alias("op"))
    total = None
    for _ in range(max_len):
        grown = step.join(edges, F.col("at") == F.col("u")).join(own, "v")
        step = stored(grown.select("src", F.col("v").alias("at"), (F.col("x") * F.col("p")).alias("x"), ((F.col("o") + (2 * F.col("phi") - 1) * F.col("op")) / 2).alias("op")), "walks")
        one = step.groupBy(F.col("src").alias("id")).agg(F.sum(F.col("x") * F.when(F.col("op") < 0, lam * F.col("op")).otherwise(F.col("op"))).alias("s"))
        total = one if total is None else total.union(one)
    sums = total.groupBy("id").agg(F.sum("s").alias("score"))
    return g.nodes.select("id").join(sums, "id", "left").select("id", F.coalesce("score", F.lit(0.0)).alias("score"))


def path_opinion_spread(path: DataFrame) -> DataFrame:
    """Closed form on one path per ``path_id``, rows (path_id, pos, o, p, phi) with p and phi of the arc
    into ``pos`` (pos 0 is the seed): expected opinion spread of the first node."""
    arr = path.groupBy("path_id").agg(F.array_sort(F.collect_list(F.struct("pos", "o", "p", "phi"))).alias("a"))
    start = F.struct(F.lit(1.0).alias("x"), F.element_at("a", 1)["o"].alias("op"), F.lit(0.0).alias("total"))

    def step(acc, r):
        x = acc["x"] * r["p"]
        op = (r["o"] + (2 * r["phi"] - 1) * acc["op"]) / 2
        return F.struct(x.alias("x"), op.alias("op"), (acc["total"] + x * op).alias("total"))

    return arr.select("path_id", F.aggregate(F.slice("a", 2, F.greatest(F.size("a") - 1, F.lit(0))), start, step)["total"].alias("spread"))


def walk_score_live_edge(g: InfluenceGraph, live: DataFrame, worlds: int, max_len: int = 3) -> DataFrame:
    """Mean over sampled live-edge worlds (world, u, v) of the walk score with p = 1."""
    edges = live.select("world", "u", "v", F.lit(1.0).alias("p"))
    state = None
    for _ in range(max_len):
        state = edges.groupBy("world", F.col("u").alias("id")).agg(F.sum("p").alias("score")) if state is None else _next_walk(edges, state, ["world"])
    sums = state.groupBy("id").agg((F.sum("score") / worlds).alias("score"))
    return g.nodes.select("id").join(sums, "id", "left").select("id", F.coalesce("score", F.lit(0.0)).alias("score"))


def score_topk(scores: DataFrame, k: int) -> DataFrame:
    """(rank, id, score) of the k best, ties to the lower id: one top-k without a full sort."""
    top = scores.orderBy(F.desc("score"), "id").limit(k)
    from pyspark.sql import Window

    return top.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("score"), "id"))).select("rank", "id", "score")


def rescore_delta(g: InfluenceGraph, scores: DataFrame, removed: DataFrame, max_len: int = 3, opinion: bool = False) -> DataFrame:
    """Scores after the nodes in ``removed`` (id) leave: only nodes that reach one of them within
    ``max_len`` arcs are scored anew, on the arcs they can reach; all others keep theirs."""
    gone = stored(removed.select("id").distinct(), "gone")
    touched = gone
    for _ in range(max_len):
        back = g.edges.join(touched.withColumnRenamed("id", "v"), "v", "left_semi").select(F.col("u").alias("id"))
        touched = stored(touched.union(back).distinct(), "touched")
    need = touched
    for _ in range(max_len):
        ahead = g.edges.join(need.withColumnRenamed("id", "u"), "u", "left_semi").select(F.col("v").alias("id"))
        need = stored(need.union(ahead).distinct(), "need")
    part = g.induced(need).without(gone)
    fresh = assign_score(part, max_len, opinion).join(touched, "id", "left_semi")
    kept = scores.join(touched, "id", "left_anti").select("id", "score")
    return kept.union(fresh.select("id", "score"))
