"""Registered queries: methods, variants, baselines, measures and experiment workloads."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rippletide import oracles as oracle_text
from rippletide.operators import baselines, churn, diffusion, errors, graphs, params, scores, seeds, similar, spread, topics
from rippletide.functions.rng import u01
from rippletide.operators.graphs import InfluenceGraph, graph
from rippletide.plans.storage import stored
from rippletide.sources.tables import table

MODE = "md5"
Query = Callable[[SparkSession, str], DataFrame]
REGISTRY: dict[str, Query] = {}


def query(f: Query) -> Query:
    REGISTRY[f.__name__.strip("_")] = f
    return f


def r6(c: Column | str) -> Column:
    return F.round(F.col(c) if isinstance(c, str) else c, 6) + 0.0


def rounded(df: DataFrame, *names: str, digits: int = 6) -> DataFrame:
    return df.withColumns({c: F.round(F.col(c), digits) + 0.0 for c in names})


def base_graph(spark: SparkSession, d: str, p: str = "ic", source: str = "cop") -> InfluenceGraph:
    """The benchmark graph with hashed opinions and interactions, stored once per query."""
    edges = graphs.copurchase_edges(spark, d) if source == "cop" else graphs.succession_edges(spark, d)
    g = graph(stored(edges.select("u", "v"), "edges"))
    g = params.interactions_uniform(params.opinions_uniform(params.assign_lt(g, mode=MODE), mode=MODE), mode=MODE)
    return (params.assign_wc(g) if p == "wc" else g).materialized()


def flagship(spark: SparkSession, d: str) -> DataFrame:
    return scores.score_topk(scores.walk_score(base_graph(spark, d), 3), 10)


def _plain(name: str, make: Callable[[SparkSession, str], DataFrame]) -> None:
    REGISTRY[name] = make


_plain("graph_copurchase", lambda s, d: graphs.copurchase_edges(s, d))
_plain("graph_succession", lambda s, d: graphs.succession_edges(s, d))
_plain("graph_trade", lambda s, d: graphs.trade_edges(s, d, 2))
_plain("graph_tree", lambda s, d: graphs.tree_edges(s, d))
_plain("graph_order_dag", lambda s, d: graphs.order_dag_edges(s, d))
_plain("graph_conversation_paths", lambda s, d: graphs.conversation_edges(s, d))
_plain("graph_similarity", lambda s, d: graphs.similarity_edges(s, d))
_plain("graph_embedding", lambda s, d: rounded(graphs.embedding_edges(s, d), "p"))
_plain("graph_links", lambda s, d: graphs.link_edges(s, d))
_plain("graph_copies", lambda s, d: graphs.copy_edges(s, d))
_plain("graph_profile", lambda s, d: graphs.profile(graph(graphs.copurchase_edges(s, d)), 2))
_plain("graph_profile_sketch", lambda s, d: graphs.profile_sketch(graph(graphs.succession_edges(s, d)).materialized()))
_plain("graph_violations", lambda s, d: graphs.violations(base_graph(s, d)))
_plain("graph_normalize", lambda s, d: rounded(graphs.normalize(base_graph(s, d)).edges, "p", "w", "phi"))
_plain("symmetrize", lambda s, d: graphs.symmetrize(graphs.succession_edges(s, d).select("u", "v")))
_plain("project_graph", lambda s, d: topics.project_graph(graphs.succession_edges(s, d).select("u", "v"), topics.topic_posts(s, d).where("topic = 7")))
_plain("assign_ic", lambda s, d: params.assign_ic(graph(graphs.copurchase_edges(s, d).select("u", "v"))).edges.select("u", "v", "p"))
_plain("assign_wc", lambda s, d: rounded(params.assign_wc(graph(graphs.copurchase_edges(s, d).select("u", "v"))).edges.select("u", "v", "p"), "p"))
_plain("opinions_uniform", lambda s, d: rounded(params.opinions_uniform(graph(graphs.copurchase_edges(s, d)), mode=MODE).nodes.select("id", "o"), "o"))
_plain("opinions_normal", lambda s, d: rounded(params.opinions_normal(graph(graphs.copurchase_edges(s, d)), mode=MODE).nodes.select("id", "o"), "o"))
_plain("interactions_uniform", lambda s, d: rounded(params.interactions_uniform(graph(graphs.copurchase_edges(s, d).select("u", "v")), mode=MODE).edges.select("u", "v", "phi"), "phi"))


@query
def assign_lt(s: SparkSession, d: str) -> DataFrame:
    g = params.assign_lt(graph(graphs.copurchase_edges(s, d).select("u", "v")), mode=MODE)
    return rounded(g.edges.join(g.nodes.select(F.col("id").alias("v"), "theta"), "v").select("u", "v", "w", "theta"), "w", "theta")


def _score(name: str, make: Callable[[InfluenceGraph], DataFrame], p: str = "ic") -> None:
    REGISTRY[name] = lambda s, d: rounded(make(base_graph(s, d, p)), "score")


for _l in (1, 3, 5):
    _score(f"walk_score_l{_l}", lambda g, n=_l: scores.walk_score(g, n))
_score("walk_score_wc", lambda g: scores.walk_score(g, 3), "wc")
_score("walk_score_lt", lambda g: scores.walk_score(g.with_p("w"), 3))
_score("walk_score_profile", lambda g: scores.walk_score_profile(g, 3))
_score("opinion_walk_score_l1", lambda g: scores.opinion_walk_score(g, 1))
_score("opinion_walk_score_l3", lambda g: scores.opinion_walk_score(g, 3))
_score("opinion_walk_score_normal", lambda g: scores.opinion_walk_score(params.opinions_normal(g, mode=MODE), 3))
_score("union_walk_score_l2", lambda g: scores.union_walk_score(g, 2))
_score("union_walk_score_l3", lambda g: scores.union_walk_score(g, 3))
_score("simple_path_score", lambda g: scores.simple_path_score(g, 3))
_score("opinion_path_score_lam0", lambda g: scores.opinion_path_score(g, 2, 0.0))
_score("opinion_path_score_lam1", lambda g: scores.opinion_path_score(g, 2, 1.0))
_score("score_topk", lambda g: scores.score_topk(scores.walk_score(g, 3), 10))
_score("walk_score_live_edge", lambda g: scores.walk_score_live_edge(g, diffusion.live_edges(g, 8, mode=MODE), 8, 2))
_plain("walk_counts", lambda s, d: scores.walk_counts(base_graph(s, d), 2))


@query
def rescore_delta(s: SparkSession, d: str) -> DataFrame:
    g = base_graph(s, d)
    full = stored(scores.walk_score(g, 3), "scores")
    best = full.orderBy(F.desc("score"), "id").limit(1)
    return rounded(scores.rescore_delta(g, full, best, 3), "score")


def top(g: InfluenceGraph, k: int = 3) -> DataFrame:
    return seeds.degree_seeds(g, k).select("id")


def _cascade(name: str, run: Callable[[InfluenceGraph, DataFrame], DataFrame], p: str = "ic", opinions: bool = False) -> None:
    def make(s: SparkSession, d: str) -> DataFrame:
        g = base_graph(s, d, p)
        act = run(g, top(g))
        return rounded(act.select("world", "id", "step", "parent", "o_final"), "o_final") if opinions else act.select("world", "id", "step")

    REGISTRY[name] = make


KW = {"worlds": 8, "mode": MODE}
_cascade("cascade_ic", lambda g, k: diffusion.cascade_ic(g, k, **KW))
_cascade("cascade_wc", lambda g, k: diffusion.cascade_ic(g, k, **KW), "wc")
_cascade("cascade_lt", lambda g, k: diffusion.cascade_lt(g, k, **KW))
_cascade("cascade_oi_ic", lambda g, k: diffusion.cascade_ic(g, k, **KW), opinions=True)
_cascade("cascade_oc_ic", lambda g, k: diffusion.cascade_ic(g, k, interaction=False, **KW), opinions=True)
_cascade("cascade_oi_lt", lambda g, k: diffusion.cascade_lt(g, k, **KW), opinions=True)
_cascade("cascade_oc", lambda g, k: diffusion.cascade_lt(g, k, interaction=False, **KW), opinions=True)
_cascade("cascade_oi_wc", lambda g, k: diffusion.cascade_ic(g, k, **KW), "wc", opinions=True)
_plain("live_edges", lambda s, d: diffusion.live_edges(base_graph(s, d), 4, mode=MODE))
_plain("sample_worlds", lambda s, d: diffusion.sample_worlds(base_graph(s, d), 4, mode=MODE))


@query
def cascade_live_edge(s: SparkSession, d: str) -> DataFrame:
    g = base_graph(s, d)
    return diffusion.cascade_worlds(g, top(g), diffusion.live_edges(g, 8, mode=MODE), 8).select("world", "id")


@query
def reach_bits(s: SparkSession, d: str) -> DataFrame:
    g = base_graph(s, d)
    return diffusion.reach_bits(g, top(g), 1, mode=MODE).select("id", F.bit_count("bits").cast("long").alias("worlds")).where("worlds > 0")


def _act(s: SparkSession, d: str) -> DataFrame:
    g = base_graph(s, d)
    return diffusion.cascade_ic(g, top(g), **KW)


_plain("activation_probability", lambda s, d: rounded(spread.activation_probability(_act(s, d), 8).select("id", "probability"), "probability"))
_plain("expected_spread", lambda s, d: rounded(spread.expected(spread.spread(_act(s, d)), 8).select("spread"), "spread"))
_plain("spread_stderr", lambda s, d: rounded(spread.expected(spread.spread(_act(s, d)), 8).select("spread", "stderr"), "spread", "stderr"))
_plain("opinion_spread", lambda s, d: rounded(spread.opinion_spread(_act(s, d)).select("world", "spread"), "spread"))
for _n, _v in (("0", 0.0), ("05", 0.5), ("1", 1.0)):
    _plain(f"effective_spread_lam{_n}", lambda s, d, v=_v: rounded(spread.expected(spread.opinion_spread(_act(s, d), v), 8).select("spread"), "spread"))


@query
def marginal_gain(s: SparkSession, d: str) -> DataFrame:
    g = base_graph(s, d)
    first, *rest = sorted(r["id"] for r in top(g).collect())
    return rounded(spread.marginal_gain(g, [first], rest, **KW), "gain")


_plain("exact_spread_toy", lambda s, d: rounded(spread.exact_spread(graphs.toy_graph(s)), "spread"))
_plain("exact_opinion_spread_toy", lambda s, d: rounded(spread.exact_spread(graphs.toy_graph(s), opinion=True), "spread"))


def _seeds(name: str, make: Callable[[InfluenceGraph], DataFrame], p: str = "ic") -> None:
    REGISTRY[name] = lambda s, d: rounded(make(base_graph(s, d, p)), "score")


_seeds("score_greedy_k3_seed", lambda g: seeds.score_greedy_seeds(g, 3, discount="seed"))
_seeds("score_greedy_k3_majority", lambda g: seeds.score_greedy_seeds(g, 3, **KW))
_seeds("score_greedy_k3_delta", lambda g: seeds.score_greedy_seeds(g, 3, discount="seed", delta=True))
_seeds("opinion_score_greedy_k3", lambda g: seeds.score_greedy_seeds(g, 3, opinion=True, discount="seed"))
_seeds("mc_greedy_k2", lambda g: seeds.mc_greedy_seeds(g, 2, **KW))
_seeds("opinion_mc_greedy_k2", lambda g: seeds.mc_greedy_seeds(g, 2, objective="opinion", **KW))
_seeds("oc_greedy_k2", lambda g: seeds.mc_greedy_seeds(g, 2, objective="opinion", model="oc", **KW))
_seeds("lazy_greedy_k2", lambda g: seeds.lazy_greedy_seeds(g, 2, **KW))
_seeds("rr_cover_k3", lambda g: baselines.max_cover(baselines.rr_sets(g, 200, mode=MODE), 3), "wc")


@query
def rr_seeds(s: SparkSession, d: str) -> DataFrame:
    """With how many reverse sets the bound asks for and how many were drawn."""
    chosen, report = baselines.rr_seeds(base_graph(s, d, "wc"), 3, eps=0.5)
    return chosen.select("*", *[F.lit(report[c]).alias(c) for c in ("wanted", "drawn", "truncated")])


_seeds("influence_rank", lambda g: baselines.influence_rank(g, rounds=5))
_seeds("influence_rank_seeds_k2", lambda g: baselines.influence_rank_seeds(g, 2, rounds=5))
_seeds("simpath_k2", lambda g: baselines.simpath_seeds(g, 2, eta=0.05, max_len=4))
_seeds("degree_seeds", lambda g: seeds.degree_seeds(g, 5))
_seeds("random_seeds", lambda g: seeds.random_seeds(g, 5, mode=MODE))
_plain("brute_force_toy", lambda s, d: rounded(seeds.brute_force_seeds(graphs.toy_graph(s), 2, 64, mode=MODE), "score"))
_plain("path_mass", lambda s, d: rounded(errors.path_mass(base_graph(s, d), 2), "mass"))
_plain("contribution", lambda s, d: rounded(errors.contribution(base_graph(s, d), 2), "summed", "united"))
_plain("dag_bounds", lambda s, d: rounded(errors.dag_bounds(graph(graphs.order_dag_edges(s, d)).materialized(), 2, 0.1), "union_bound", "walk_bound", "total_bound"))
_plain("cycle_error", lambda s, d: rounded(errors.cycle_error(base_graph(s, d), 3), "error"))
_plain("expected_path_mass", lambda s, d: rounded(errors.expected_path_mass(table(s, d, "orders").select(F.col("o_custkey").alias("u")), 0.1, 8), "mass", "cycle_mass", "critical"))
_plain("repeated_paths", lambda s, d: rounded(errors.repeated_paths(graphs.nation_part_paths(s, d), 0.5, 3), "united", "summed"))
_plain("order_condition", lambda s, d: errors.order_condition(scores.walk_score(graphs.toy_graph(s), 3), spread.exact_spread(graphs.toy_graph(s))))
@query
def submodularity_two_layer(s: SparkSession, d: str) -> DataFrame:
    """The first customer with orders, the last one, whose arcs turn opinions round, and the second."""
    g = graphs.order_layer_graph(s, d)
    ends = g.edges.select("u").distinct()
    low, high = [r["u"] for r in ends.orderBy("u").limit(2).collect()], [r["u"] for r in ends.orderBy(F.desc("u")).limit(1).collect()]
    return rounded(errors.submodularity(s, g, [*low[:1], *high, *low[1:]]), "spread")



_plain("tree_exactness", lambda s, d: rounded(scores.walk_score(graph(graphs.tree_edges(s, d)).materialized(), 3).where("score > 0"), "score"))


_plain("submodularity_violations", lambda s, d: errors.violations(graphs.two_layer_graph(s, 4), [1, 2, 3, 4]))


@query
def violation_window(s: SparkSession, d: str) -> DataFrame:
    counts = stored(graphs.nation_part_paths(s, d).select("t").distinct(), "counts")
    return rounded(errors.violation_window(counts, 0.1), "gap")


@query
def set_decomposition(s: SparkSession, d: str) -> DataFrame:
    """Spread of the first seed, of the others beyond it, and of all, in common worlds."""
    g = base_graph(s, d)
    first, *rest = sorted(r["id"] for r in top(g).collect())
    runs = s.createDataFrame([(0, first), *[(1, x) for x in rest], *[(2, x) for x in (first, *rest)]], "run long, id long")
    return errors.decomposition(diffusion.cascade_ic(g, runs, **KW), 0, 1, 2)


@query
def lt_equals_live_edge(s: SparkSession, d: str) -> DataFrame:
    """Mean spread under thresholds and along live edges: two draws of one distribution."""
    g, worlds = base_graph(s, d), 64
    by = {"thresholds": diffusion.cascade_lt(g, top(g), worlds, mode=MODE), "live edges": diffusion.cascade_worlds(g, top(g), diffusion.live_edges(g, worlds, mode=MODE), worlds)}
    out = None
    for name, act in by.items():
        one = act.agg((F.count(F.when(F.col("step") > 0, 1)) / worlds).alias("spread")).select(F.lit(name).alias("model"), r6("spread").alias("spread"))
        out = one if out is None else out.union(one)
    return out


@query
def dag_lt_exactness(s: SparkSession, d: str) -> DataFrame:
    """On a DAG under linear threshold the walk score is the exact spread: the sum over its paths."""
    g = params.assign_lt(graph(graphs.order_dag_edges(s, d))).materialized()
    return rounded(scores.walk_score(g.with_p("w"), 2).where("score > 0"), "score")


@query
def path_closed_form(s: SparkSession, d: str) -> DataFrame:
    """Expected opinion spread of each conversation's first turn along its path."""
    c = table(s, d, "conversations").select(F.col("conv_id").alias("path_id"), (F.col("conv_id") * 1_000_000 + F.col("turn")).alias("id"), "turn")
    order = Window.partitionBy("path_id").orderBy("turn")
    c = c.withColumn("pos", F.row_number().over(order) - 1).withColumn("before", F.lag("id").over(order))
    rows = c.select("path_id", "pos", (2 * u01("o", 1, F.col("id"), mode=MODE) - 1).alias("o"), F.lit(0.5).alias("p"), u01("phi", 1, F.col("before"), F.col("id"), mode=MODE).alias("phi"))
    return rounded(scores.path_opinion_spread(rows), "spread")


@query
def set_cover_instance(s: SparkSession, d: str) -> DataFrame:
    out = None
    for kind, sets in (("cover", [[0, 1], [2, 3], [1, 2]]), ("none", [[0, 1], [1, 2], [0, 2]])):
        g = graphs.set_cover_graph(s, 4, sets)
        runs = spread.subsets(s, [1, 2, 3], 2)
        best = spread.expected_spread(g, runs, 1, objective="opinion", mode=MODE).agg(F.max("spread").alias("spread"))
        one = best.select(F.lit(kind).alias("kind"), r6("spread").alias("spread"))
        out = one if out is None else out.union(one)
    return out


@query
def rank_agreement(s: SparkSession, d: str) -> DataFrame:
    g = base_graph(s, d, source="suc")
    keep = g.edges.select(F.col("u").alias("id")).distinct()
    one, three = (scores.walk_score(g, n).join(keep, "id", "left_semi") for n in (1, 3))
    return rounded(errors.rank_agreement(one, three, 10).select("concordant", "discordant", "tau"), "tau")


def _topic_tables(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    background = stored(graphs.succession_edges(s, d).select("u", "v"), "background")
    members = stored(topics.topic_members(topics.epochs_by_post(topics.topic_posts(s, d))), "members")
    edges = stored(topics.topic_edges(members, background), "topic_edges")
    return background, members, edges, topics.originators(members, edges)


_plain("topic_posts", lambda s, d: rounded(topics.topic_posts(s, d).groupBy("topic").agg(F.count(F.lit(1)).alias("posts"), F.avg("opinion").alias("opinion")), "opinion"))
_plain("gap_threshold", lambda s, d: rounded(topics.gap_threshold(topics.topic_posts(s, d)), "threshold", digits=3))
_plain("topic_epochs_post", lambda s, d: topics.epochs_by_post(topics.topic_posts(s, d)).groupBy("topic", "epoch").agg(F.count(F.lit(1)).alias("posts")))
_plain("topic_epochs_seed", lambda s, d: topics.epochs_by_seed(topics.topic_posts(s, d), graphs.succession_edges(s, d).select("u", "v")).groupBy("topic", "epoch").agg(F.count(F.lit(1)).alias("posts")))
_plain("topic_edges", lambda s, d: _topic_tables(s, d)[2])
_plain("originators", lambda s, d: _topic_tables(s, d)[3])
_plain("top_topics", lambda s, d: topics.top_topics(topics.topic_posts(s, d), 10))
_plain("post_opinion", lambda s, d: rounded(topics.topic_posts(s, d).select("event_id", "opinion"), "opinion", digits=8))
_plain("true_opinion", lambda s, d: rounded(topics.true_opinion(topics.topic_posts(s, d)), "opinion", digits=8))
_plain("estimated_opinion", lambda s, d: rounded(topics.estimate_opinion(topics.topic_posts(s, d)), "truth", "estimate", digits=8))
_plain("opinion_error", lambda s, d: rounded(topics.nrmse(topics.estimate_opinion(topics.topic_posts(s, d)), "estimate", "truth", by=["topic"]).where("nrmse is not null"), "nrmse"))


@query
def opinion_error_split(s: SparkSession, d: str) -> DataFrame:
    """Error of the estimated opinions of users who start a topic's subgraph somewhere, and of the others."""
    origin = _topic_tables(s, d)[3].select("topic", "user_id").distinct().withColumn("node", F.lit("seed"))
    rows = topics.estimate_opinion(topics.topic_posts(s, d)).join(origin, ["topic", "user_id"], "left").withColumn("node", F.coalesce("node", F.lit("other")))
    return rounded(topics.nrmse(rows, "estimate", "truth", by=["node"]), "nrmse")


@query
def estimated_interaction(s: SparkSession, d: str) -> DataFrame:
    background, members, _, _ = _topic_tables(s, d)
    return rounded(topics.estimate_interaction(members, background), "phi")


@query
def ground_truth_spread(s: SparkSession, d: str) -> DataFrame:
    _, members, _, origin = _topic_tables(s, d)
    return rounded(topics.ground_truth_spread(members, origin), "spread")


_plain("churn_labels", lambda s, d: churn.churn_labels(s, d))
_plain("balanced_sample", lambda s, d: churn.balanced_sample(churn.churn_labels(s, d), "label", mode=MODE))


def churn_rows(s: SparkSession, d: str) -> DataFrame:
    """(id, f1..f4, label) of every customer."""
    return similar.features(s, d).join(churn.churn_labels(s, d).select("id", F.col("label").cast("double").alias("label")), "id", "left").withColumn("label", F.coalesce("label", F.lit(0.0)))


_plain("label_propagation_t5", lambda s, d: rounded(similar.propagate(stored(churn_rows(s, d), "labels"), rounds=5), "value"))


def queries() -> dict[str, Query]:
    from rippletide import reports
    from rippletide.operators import relational
    from rippletide.streaming import topics as stream

    return REGISTRY | reports.queries() | relational.queries() | stream.queries()


def oracles() -> dict[str, str]:
    from rippletide.operators import relational
    from rippletide.streaming import topics as stream

    return oracle_text.sql() | relational.oracles() | stream.oracles()
