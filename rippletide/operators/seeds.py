"""Seed selection: score greedy, simulated greedy, lazy greedy, and simple floors.

The driver holds the seeds chosen so far and one batch of candidates' gains; everything per node
stays in DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rippletide.functions.rng import u01
from rippletide.operators import scores, spread
from rippletide.operators.graphs import InfluenceGraph
from rippletide.plans.storage import small, stored, stored_with_count

SEEDS = "rank int, id long, score double"


def _best(scored: DataFrame, allow_nonpositive: bool) -> tuple[int, float] | None:
    row = scored.orderBy(F.desc("score"), "id").limit(1).collect()
    return (row[0]["id"], row[0]["score"]) if row and (allow_nonpositive or row[0]["score"] > 0) else None


def activated_by(g: InfluenceGraph, seed: int, discount: str, worlds: int, share: float, **kw) -> DataFrame:
    """(id) that count as activated once ``seed`` is chosen: the seed alone, those of one cascade, or
    those activated in more than ``share`` of the worlds."""
    spark = g.nodes.sparkSession
    one = spark.createDataFrame([(seed,)], "id long")
    if discount == "seed":
        return one
    n = 1 if discount == "world0" else worlds
    act = spread.simulate(g, one, n, **kw)
    often = act.groupBy("id").agg((F.count(F.lit(1)) / n).alias("share"))
    return often.where(F.col("share") > (0.5 if discount == "majority" else 0.0 if discount == "world0" else share)).select("id").union(one).distinct()


def score_greedy_seeds(g: InfluenceGraph, k: int, max_len: int = 3, opinion: bool = False, discount: str = "majority", worlds: int = 32, share: float = 0.5, candidates: DataFrame | None = None, allow_nonpositive: bool = False, delta: bool = False, **kw) -> DataFrame:
    """(rank, id, score): score all nodes, take the best, take away what it activates, repeat. With
    ``delta`` later rounds score only nodes near the removed ones. Stops early when no score is
    positive, unless ``allow_nonpositive``."""
    spark = g.nodes.sparkSession
    chosen: list[tuple[int, int, float]] = []
    left, scored, gone, n_gone = g, None, None, 0
    for _ in range(k):
        if scored is None or not delta:
            scored = scores.assign_score(left, max_len, opinion)
            scored = stored(scored, "scores") if delta else scored
        pool = scored if gone is None else scored.join(small(gone, n_gone), "id", "left_anti")
        best = _best(pool if candidates is None else pool.join(candidates.select("id"), "id", "left_semi"), allow_nonpositive)
        if best is None:
            break
        chosen.append((len(chosen) + 1, *best))
        if len(chosen) < k:
            # The graph is never written anew: what is left is the stored arcs without the removed ids.
            if discount == "seed":
                new = spark.createDataFrame([(best[0],)], "id long")
                gone, n_gone = spark.createDataFrame([(c[1],) for c in chosen], "id long"), len(chosen)
            else:
                new = stored(activated_by(left, best[0], discount, worlds, share, **kw), "gone")
                gone, n_gone = stored_with_count(new if gone is None else gone.union(new).distinct(), "gone")
            if delta:
                scored = stored(scores.rescore_delta(left, scored, new, max_len, opinion), "scores")
            left = g.without(small(gone, n_gone))
    return spark.createDataFrame(chosen, SEEDS)


def _gains(g: InfluenceGraph, chosen: list[int], candidates: list[int], worlds: int, objective: str, lam: float, **kw) -> dict[int, float]:
    spark = g.nodes.sparkSession
    rows = spark.createDataFrame([(c, s) for c in candidates for s in [*chosen, c]], "run long, id long")
    act = spread.simulate(g, rows, worlds, **kw)
    per = spread.spread(act) if objective == "count" else spread.opinion_spread(act, lam)
    return {r["run"]: r["spread"] for r in spread.expected(per, worlds).select("run", "spread").collect()}


def mc_greedy_seeds(g: InfluenceGraph, k: int, worlds: int, objective: str = "count", lam: float = 1.0, candidates: list[int] | None = None, batch: int = 2000, **kw) -> DataFrame:
    """(rank, id, score): in each round the candidate with the largest simulated spread of the seeds and
    itself; all candidates of a batch run in one cascade on common worlds. score is that spread."""
    spark = g.nodes.sparkSession
    pool = sorted(candidates if candidates is not None else [r["id"] for r in g.nodes.select("id").toLocalIterator()])
    chosen: list[tuple[int, int, float]] = []
    for rank in range(1, min(k, len(pool)) + 1):
        taken = [c[1] for c in chosen]
        free = [c for c in pool if c not in taken]
        value: dict[int, float] = {}
        for i in range(0, len(free), batch):
            value |= _gains(g, taken, free[i : i + batch], worlds, objective, lam, **kw)
        best = min(free, key=lambda c: (-round(value.get(c, 0.0), 9), c))
        chosen.append((rank, best, float(value.get(best, 0.0))))
    return spark.createDataFrame(chosen, SEEDS)


def lazy_greedy_seeds(g: InfluenceGraph, k: int, worlds: int, candidates: list[int] | None = None, batch: int = 32, first_batch: int = 2000, **kw) -> DataFrame:
    """(rank, id, score) as the plain greedy on the same worlds, with stale gains re-evaluated only at
    the top, a batch a job; the first round takes all candidates, ``first_batch`` a job. Each evaluation also looks one seed ahead: next to a node's own gain it
    takes the gain over the best node seen so far, which is its next gain should that node be chosen."""
    spark = g.nodes.sparkSession
    pool = sorted(candidates if candidates is not None else [r["id"] for r in g.nodes.select("id").toLocalIterator()])
    chosen: list[int] = []
    out: list[tuple[int, int, float]] = []
    base = 0.0
    # Totals (spread of chosen + node) bound later totals only through gains: total - base + 1 counts
    # the node itself, which leaves the spread when it becomes a seed.
    first: dict[int, float] = {}
    for i in range(0, len(pool), first_batch):
        first |= _gains(g, [], pool[i : i + first_batch], worlds, "count", 1.0, **kw)
    gain = {c: first.get(c, 0.0) + 1 for c in pool}
    fresh = dict.fromkeys(pool, 0)
    ahead: dict[int, tuple[int, float]] = {}
    evaluations = len(pool)
    for rank in range(1, min(k, len(pool)) + 1):
        while True:
            order = sorted((c for c in pool if c not in chosen), key=lambda c: (-round(gain[c], 9), c))
            if fresh[order[0]] == len(chosen):
                break
            stale = []
            for c in order[:batch]:
                if fresh[c] == len(chosen):
                    continue
                if chosen and ahead.get(c, (None, 0.0))[0] == chosen[-1] and fresh[c] == len(chosen) - 1:
                    gain[c], fresh[c] = ahead[c][1], len(chosen)
                else:
                    stale.append(c)
            if stale:
                value = _gains(g, chosen, stale, worlds, "count", 1.0, **kw)
                evaluations += len(stale)
                for c in stale:
                    gain[c], fresh[c] = value.get(c, 0.0) - base + 1, len(chosen)
        best = order[0]
        total = base + gain[best] - 1
        out.append((rank, best, float(total)))
        if rank < k:
            leader = order[1 : 1 + batch]
            look = _gains(g, [*chosen, best], leader, worlds, "count", 1.0, **kw) if leader else {}
            evaluations += len(leader)
            ahead |= {c: (best, look.get(c, 0.0) - total + 1) for c in leader}
        chosen.append(best)
        base = total
    return spark.createDataFrame(out, SEEDS)


def degree_seeds(g: InfluenceGraph, k: int) -> DataFrame:
    return scores.score_topk(g.edges.groupBy(F.col("u").alias("id")).agg(F.count(F.lit(1)).cast("double").alias("score")), k)


def random_seeds(g: InfluenceGraph, k: int, seed: int = 1, mode: str = "xxhash") -> DataFrame:
    return scores.score_topk(g.nodes.select("id", u01("pick", seed, F.col("id"), mode=mode).alias("score")), k)


def brute_force_seeds(g: InfluenceGraph, k: int, worlds: int, objective: str = "count", lam: float = 1.0, **kw) -> DataFrame:
    """Best k-subset of a small node set by simulation of every subset: (rank, id, score)."""
    ids = [r["id"] for r in g.nodes.limit(33).collect()]
    if len(ids) > 32:
        raise ValueError("for at most 32 nodes")
    runs = spread.subsets(g.nodes.sparkSession, ids, k)
    res = spread.expected_spread(g, runs, worlds, objective=objective, lam=lam, **kw)
    best = res.orderBy(F.desc(F.round("spread", 9)), "run").limit(1).select("run", "spread")
    rank = F.row_number().over(Window.partitionBy("run").orderBy("id"))
    return runs.join(F.broadcast(best), "run").select(rank.alias("rank"), "id", F.col("spread").alias("score"))
