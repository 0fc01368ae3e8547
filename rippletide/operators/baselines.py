"""Published competitors, rebuilt on joins: reverse-reachable sampling, influence rank, simple paths."""

from __future__ import annotations

from math import ceil, lgamma, log, log2

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rippletide.functions.rng import u01
from rippletide.operators.diffusion import joined, steps_to
from rippletide.operators.graphs import InfluenceGraph
from rippletide.operators.scores import simple_paths
from rippletide.operators.seeds import SEEDS
from rippletide.plans.storage import stored, stored_with_count


def rr_sets(g: InfluenceGraph, count: int, offset: int = 0, seed: int = 1, max_steps: int | None = None, mode: str = "xxhash") -> DataFrame:
    """(rr, id): ``count`` reverse-reachable sets, each of the nodes that reach a random root in a world
    of its own. The root is the node with rank floor(draw * n) by id."""
    spark = g.nodes.sparkSession
    index = stored(_ranked(g.nodes.select("id")), "index")
    n = index.count()
    draws = spark.range(offset, offset + count).select(F.col("id").alias("rr"), F.floor(u01("root", seed, F.col("id"), mode=mode) * n).cast("long").alias("k"))
    found, size = stored_with_count(draws.join(index, "k").select("rr", "id"), "rr")
    front, edges = found, g.edges.select("u", "v", "p")
    for t in steps_to(max_steps):
        if not size:
            break
        back = edges.join(front.withColumnRenamed("id", "v"), "v").where(u01("rr", seed, F.col("rr"), F.col("u"), F.col("v"), mode=mode) < F.col("p")).select("rr", F.col("u").alias("id")).distinct()
        front, size = stored_with_count(back.join(found, ["rr", "id"], "left_anti"), "rr")
        found = joined(found, front, t)
    return found


def _ranked(ids: DataFrame) -> DataFrame:
    """(k, id): dense rank from 0 by id, without ordering everything in one task: range partitions,
    counts per partition, positions within."""
    from pyspark.sql import Window

    parts = ids.repartitionByRange("id").select("id", F.spark_partition_id().alias("part"))
    parts = stored(parts, "ranges")
    sizes = parts.groupBy("part").agg(F.count(F.lit(1)).alias("c"), F.min("id").alias("low"))
    before = F.coalesce(F.sum("c").over(Window.orderBy("low").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    base = sizes.select("part", before.alias("base"))
    inside = F.row_number().over(Window.partitionBy("part").orderBy("id"))
    return parts.withColumn("r", inside).join(base, "part").select((F.col("base") + F.col("r") - 1).alias("k"), "id")


def max_cover(sets: DataFrame, k: int) -> DataFrame:
    """(rank, id, score): greedy cover of the sets; score is how many yet uncovered sets hold the node."""
    out, left = [], sets
    for rank in range(1, k + 1):
        best = left.groupBy("id").agg(F.count(F.lit(1)).alias("c")).orderBy(F.desc("c"), "id").limit(1).collect()
        if not best:
            break
        out.append((rank, best[0]["id"], float(best[0]["c"])))
        if rank < k:
            hit = left.where(F.col("id") == best[0]["id"]).select("rr")
            left = stored(left.join(hit, "rr", "left_anti"), "cover")
    return sets.sparkSession.createDataFrame(out, SEEDS)


def _bounded(count: int, limit: int | None) -> int:
    return count if limit is None else min(count, limit)


def _log_choose(n: int, k: int) -> float:
    return lgamma(n + 1) - lgamma(k + 1) - lgamma(n - k + 1)


def estimate_kpt(g: InfluenceGraph, k: int, ell: float = 1.0, seed: int = 1, max_rr: int | None = None, **kw) -> tuple[float, DataFrame | None]:
    """Lower estimate of the best spread of k seeds from the widths of ever more sampled sets."""
    n, m = g.nodes.count(), g.edges.count()
    indeg = g.edges.groupBy(F.col("v").alias("id")).agg(F.count(F.lit(1)).alias("d"))
    sets = None
    for i in range(1, max(2, int(log2(max(n, 2))))):
        count = _bounded(ceil((6 * ell * log(max(n, 2)) + 6 * log(max(log2(max(n, 2)), 2))) * 2**i), max_rr)
        sets = rr_sets(g, count, seed=seed * 1000 + i, **kw)
        widths = sets.join(indeg, "id", "left").groupBy("rr").agg(F.sum(F.coalesce("d", F.lit(0))).alias("w"))
        kappa = widths.agg(F.avg(1 - F.pow(1 - F.col("w") / m, k))).first()[0] or 0.0
        if kappa > 2.0**-i:
            return n * kappa / 2, sets
        if count == max_rr:
            break
    return 1.0, sets


def refine_kpt(g: InfluenceGraph, k: int, kpt: float, sets: DataFrame, eps: float, ell: float = 1.0, seed: int = 1, max_rr: int | None = None, **kw) -> float:
    n = g.nodes.count()
    e = 5 * (ell * eps**2 / (k + ell)) ** (1 / 3)
    picked = max_cover(sets, k).select("id")
    count = _bounded(ceil((2 + e) * ell * n * log(max(n, 2)) / (e**2 * kpt)), max_rr)
    fresh = rr_sets(g, count, seed=seed * 1000 + 777, **kw)
    share = fresh.join(F.broadcast(picked), "id", "left_semi").select("rr").distinct().count() / count
    return max(kpt, share * n / (1 + e))


def rr_seeds(g: InfluenceGraph, k: int, eps: float = 0.1, ell: float = 1.0, seed: int = 1, max_rr: int | None = None, **kw) -> tuple[DataFrame, dict]:
    """Seeds by reverse-reachable sampling, and a report: the estimates, how many sets the guarantee
    asks for, how many were drawn (all, unless ``max_rr`` is given) and whether that truncated it."""
    n = g.nodes.count()
    kpt, sets = estimate_kpt(g, k, ell, seed, max_rr, **kw)
    plus = refine_kpt(g, k, kpt, sets, eps, ell, seed, max_rr, **kw) if sets is not None else kpt
    wanted = ceil((8 + 2 * eps) * n * (ell * log(max(n, 2)) + _log_choose(n, min(k, n)) + log(2)) / (eps**2 * plus))
    drawn = _bounded(wanted, max_rr)
    chosen = max_cover(rr_sets(g, drawn, seed=seed, **kw), k)
    return chosen, {"kpt": kpt, "kpt_plus": plus, "wanted": wanted, "drawn": drawn, "truncated": wanted > drawn}


def influence_rank(g: InfluenceGraph, activated: DataFrame | None = None, alpha: float = 0.7, rounds: int = 20) -> DataFrame:
    """(id, score): r(u) = (1 - ap(u)) * (1 + alpha * sum p * r(v)), from r = 1; ap is 0 unless given."""
    edges = g.edges.select("u", "v", "p")
    state = g.nodes.select("id", F.lit(1.0).alias("score"))
    ap = None if activated is None else activated.select("id", "ap")
    for i in range(rounds):
        if i % 4 == 3:
            state = stored(state, "rank")
        sums = edges.join(state.withColumnRenamed("id", "v"), "v").groupBy(F.col("u").alias("id")).agg(F.sum(F.col("p") * F.col("score")).alias("s"))
        rank = g.nodes.select("id").join(sums, "id", "left").select("id", (1 + alpha * F.coalesce("s", F.lit(0.0))).alias("score"))
        if ap is not None:
            rank = rank.join(ap, "id", "left").select("id", (F.col("score") * (1 - F.coalesce("ap", F.lit(0.0)))).alias("score"))
        state = rank
    return state


def activation_by_paths(g: InfluenceGraph, seeds: DataFrame, theta: float = 1 / 320, max_len: int = 6) -> DataFrame:
    """(id, ap): chance that the seeds activate a node, along paths of product at least ``theta``, one (the
    best) a seed and node, combined as independent; 1 for the seeds."""
    best = simple_paths(g, max_len, prune=theta, starts=seeds).groupBy("src", "dst").agg(F.max("x").alias("x"))
    ap = best.groupBy(F.col("dst").alias("id")).agg((1 - F.product(1 - F.col("x"))).alias("ap"))
    return ap.join(seeds.select("id"), "id", "left_anti").union(seeds.select("id", F.lit(1.0)))


def influence_rank_seeds(g: InfluenceGraph, k: int, alpha: float = 0.7, theta: float = 1 / 320, rounds: int = 20) -> DataFrame:
    spark = g.nodes.sparkSession
    out: list[tuple[int, int, float]] = []
    for rank in range(1, k + 1):
        seeds = spark.createDataFrame([(r[1],) for r in out], "id long")
        ap = stored(activation_by_paths(g, seeds, theta), "ap") if out else None
        r = influence_rank(g, ap, alpha, rounds).join(seeds, "id", "left_anti").orderBy(F.desc("score"), "id").limit(1).collect()
        if not r:
            break
        out.append((rank, r[0]["id"], float(r[0]["score"])))
    return spark.createDataFrame(out, SEEDS)


def path_spread(g: InfluenceGraph, eta: float = 1e-3, max_len: int = 8, starts: DataFrame | None = None) -> DataFrame:
    """(id, score): linear-threshold spread of single nodes, 1 + sum of the weights of simple paths, each
    dropped once its weight falls below ``eta``."""
    sums = simple_paths(g.with_p("w"), max_len, eta, starts).groupBy(F.col("src").alias("id")).agg(F.sum("x").alias("s"))
    nodes = g.nodes.select("id") if starts is None else starts.select("id").distinct()
    return nodes.join(sums, "id", "left").select("id", (1 + F.coalesce("s", F.lit(0.0))).alias("score"))


def simpath_seeds(g: InfluenceGraph, k: int, eta: float = 1e-3, lookahead: int = 4, max_len: int = 8, block: int = 50) -> DataFrame:
    """(rank, id, score): greedy by path spread of the set, that is the sum over seeds of the spread of each
    on the graph without the others; per round only the ``lookahead`` best stale nodes are evaluated at
    once, until the best is fresh. The driver takes the nodes of the first round ``block`` * k at a time, the
    next ones as soon as the best gain does not exceed the last one taken."""
    spark = g.nodes.sparkSession
    alone = stored(path_spread(g, eta, max_len), "alone")
    gains: dict[int, float] = {}
    fresh: dict[int, int] = {}
    last: tuple[float, int] | None = None
    more = True
    chosen: list[int] = []
    out, total = [], 0.0

    def set_spread(seeds: list[int]) -> float:
        value = 0.0
        for s in seeds:
            others = spark.createDataFrame([(x,) for x in seeds if x != s], "id long")
            value += path_spread(g.without(others), eta, max_len, spark.createDataFrame([(s,)], "id long")).first()["score"]
        return value

    while len(chosen) < k:
        order = sorted((c for c in gains if c not in chosen), key=lambda c: (-round(gains[c], 9), c))
        if more and (not order or last is None or round(gains[order[0]], 9) <= round(last[0], 9)):
            rest = alone if last is None else alone.where((F.col("score") < last[0]) | ((F.col("score") == last[0]) & (F.col("id") > last[1])))
            rows = rest.orderBy(F.desc("score"), "id").limit(block * k).collect()
            more = len(rows) == block * k
            gains |= {r["id"]: r["score"] for r in rows}
            fresh |= {r["id"]: 0 for r in rows}
            last = (rows[-1]["score"], rows[-1]["id"]) if rows else last
            continue
        if not order:
            break
        if fresh[order[0]] != len(chosen):
            for c in [c for c in order[:lookahead] if fresh[c] != len(chosen)]:
                gains[c], fresh[c] = set_spread([*chosen, c]) - total, len(chosen)
            continue
        total += gains[order[0]]
        chosen.append(order[0])
        out.append((len(chosen), order[0], float(total)))
    return spark.createDataFrame(out, SEEDS)
