"""The experiment workloads, re-expressed on the given tables as report tables.

Rows are (workload, model, k, l, lam, metric, value). Times and sizes differ from run to run, so those
reports have no SQL counterpart; the deterministic measures behind them are registered separately."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rippletide.operators import baselines, errors, graphs, params, scores, seeds, similar, spread, topics
from rippletide.operators.graphs import InfluenceGraph, graph
from rippletide.plans.cost import Meter, plan_mb
from rippletide.plans.storage import stored

SCHEMA = "workload string, model string, k int, l int, lam double, metric string, value double"
WORLDS = 16
MODE = "md5"
SIM = {"worlds": WORLDS, "mode": MODE}


class Report:
    """A growing run log of one workload."""

    def __init__(self, spark: SparkSession, name: str) -> None:
        self.spark, self.name, self.rows = spark, name, []

    def add(self, metric: str, value: float, model: str = "", k: int = 0, length: int = 0, lam: float = 1.0) -> None:
        self.rows.append((self.name, model, k, length, float(lam), metric, float(value)))

    def timed(self, run: Callable[[], DataFrame], **kw) -> DataFrame:
        with Meter(self.spark) as meter:
            out = stored(run(), "report")
        self.add("seconds", meter.seconds, **kw)
        self.add("peak_mb", meter.peak_mb, **kw)
        self.add("shuffle_mb", meter.shuffle_mb, **kw)
        self.add("rows_moved", meter.rows, **kw)
        return out

    def value(self, metric: str, model: str, k: int = 0) -> float:
        return next(r[6] for r in self.rows if r[5] == metric and r[1] == model and r[2] == k)

    def table(self) -> DataFrame:
        return self.spark.createDataFrame(self.rows, SCHEMA)


def _base(s: SparkSession, d: str, source: str = "cop", p: str = "ic") -> InfluenceGraph:
    from rippletide.workloads import base_graph

    return base_graph(s, d, p, source)


def _value(g: InfluenceGraph, chosen: DataFrame, objective: str = "count", lam: float = 1.0, model: str = "ic") -> float:
    row = spread.expected_spread(g, chosen.select("id"), objective=objective, lam=lam, model=model, **SIM).first()
    return float(row["spread"]) if row else 0.0


def deviation_pct(value: float, best: float) -> float:
    return 100.0 * (best - value) / best if best else 0.0


def gain(base: float | None, ours: float) -> float:
    """Ratio of a competitor's cost to ours; infinite where it did not finish."""
    return float("inf") if base is None else base / ours if ours else float("nan")


def w01_example(s: SparkSession, d: str) -> DataFrame:
    r, g = Report(s, "w01"), graphs.toy_graph(s)
    for name, table in (("exact", spread.exact_spread(g)), ("exact_opinion", spread.exact_spread(g, opinion=True))):
        for row in table.collect():
            r.add(f"{name}_{'ABCD'[row['id'] - 1]}", row["spread"])
    for opinion in (False, True):
        row = seeds.score_greedy_seeds(g, 1, opinion=opinion).first()
        r.add("seed", row["id"], "oi" if opinion else "ic", 1, 3)
    return r.table()


def _topics(s: SparkSession, d: str, n: int) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame, DataFrame]:
    posts = topics.topic_posts(s, d)
    posts = posts.join(F.broadcast(topics.top_topics(posts, n).select("topic")), "topic", "left_semi")
    background = stored(graphs.succession_edges(s, d).select("u", "v"), "background")
    members = stored(topics.topic_members(topics.epochs_by_post(posts)), "members")
    edges = stored(topics.topic_edges(members, background), "topic_edges")
    return posts, background, members, edges, stored(topics.originators(members, edges), "origin")


def w04_topic_models(s: SparkSession, d: str) -> DataFrame:
    """Opinion spread of the real originators under three models against the posts' own opinions, over the
    hundred largest topics."""
    r = Report(s, "w04")
    posts, background, members, edges, origin = _topics(s, d, 100)
    truth = topics.ground_truth_spread(members, origin)
    guess = topics.model_spreads(members, edges, origin, topics.estimate_opinion(posts), topics.estimate_interaction(members, background), WORLDS, mode=MODE)
    both = truth.withColumnRenamed("spread", "truth").join(guess, ["topic", "epoch"])
    for row in topics.nrmse(both, "spread", "truth", by=["model"]).collect():
        r.add("nrmse", row["nrmse"] if row["nrmse"] is not None else float("nan"), row["model"])
    return r.table()


def w05_originators(s: SparkSession, d: str) -> DataFrame:
    """The same error over the number of originators a topic starts from, earliest first."""
    r = Report(s, "w05")
    posts, background, members, edges, origin = _topics(s, d, 10)
    early = Window.partitionBy("topic", "epoch").orderBy("first_ts", "user_id")
    ranked = origin.join(members, ["topic", "epoch", "user_id"]).withColumn("place", F.row_number().over(early))
    opinions, phi = stored(topics.estimate_opinion(posts), "opinions"), stored(topics.estimate_interaction(members, background), "phi")
    for k in (1, 2, 4):
        some = stored(ranked.where(F.col("place") <= k).select("topic", "epoch", "user_id"), "some")
        truth = topics.ground_truth_spread(members, some)
        guess = topics.model_spreads(members, edges, some, opinions, phi, 4, mode=MODE)
        both = truth.withColumnRenamed("spread", "truth").join(guess, ["topic", "epoch"])
        for row in topics.nrmse(both, "spread", "truth", by=["model"]).collect():
            r.add("nrmse", row["nrmse"] if row["nrmse"] is not None else float("nan"), row["model"], k)
    return r.table()


def w06_model_choice(s: SparkSession, d: str) -> DataFrame:
    """Seeds picked for each model's objective, all valued by the opinion spread with interactions."""
    r, g = Report(s, "w06"), _base(s, d, "suc")
    for k in (2, 4):
        r.add("opinion_spread", _value(g, seeds.score_greedy_seeds(g, k, 1, True, "seed"), "opinion"), "oi", k, 1)
        r.add("opinion_spread", _value(g, seeds.score_greedy_seeds(InfluenceGraph(g.nodes, g.edges.withColumn("phi", F.lit(1.0))), k, 1, True, "seed"), "opinion"), "oc", k, 1)
        r.add("opinion_spread", _value(g, seeds.score_greedy_seeds(g, k, 1, False, "seed"), "opinion"), "ic", k, 1)
    return r.table()


def w07_churn(s: SparkSession, d: str) -> DataFrame:
    from rippletide.workloads import churn_rows

    r, rows = Report(s, "w07"), stored(churn_rows(s, d), "labels")
    value = similar.propagate(rows, max_iter=10)
    g = similar.cascade_graph(rows.drop("label").join(value.withColumnRenamed("value", "o"), "id"), mode=MODE)
    models, runs = {"oi": (True, True), "oc": (True, False), "ic": (False, True)}, None
    for run, (opinion, interaction) in enumerate(models.values()):
        one = similar.score_seeds(g, 3, 2, opinion, interaction).select(F.lit(run).alias("run"), "id")
        runs = one if runs is None else runs.union(one)
    found = {x["run"]: x["spread"] for x in spread.expected_spread(g, runs, objective="opinion", **SIM).collect()}
    for run, name in enumerate(models):
        r.add("opinion_spread", found.get(run, 0.0), name, 3, 2)
    return r.table()


def w08_penalty(s: SparkSession, d: str) -> DataFrame:
    """Seeds by the path score with and without a penalty on negative opinions, both valued with it."""
    r = Report(s, "w08")
    for source in ("cop", "suc"):
        g = _base(s, d, source)
        for lam in (0.0, 1.0):
            chosen = scores.score_topk(scores.opinion_path_score(g, 2, lam), 5)
            r.add("effective_spread", _value(g, chosen, "opinion", 1.0), source, 5, 2, lam)
    return r.table()


def w09_length_opinion(s: SparkSession, d: str) -> DataFrame:
    """Opinion spread over path length, against the simulated greedy over all nodes."""
    r, g = Report(s, "w09"), params.opinions_normal(_base(s, d), mode=MODE)
    g = g.materialized()
    for length in (1, 3, 5):
        chosen = r.timed(lambda n=length: seeds.score_greedy_seeds(g, 3, n, True, "seed"), model="walk", k=3, length=length)
        r.add("opinion_spread", _value(g, chosen, "opinion"), "walk", 3, length)
    chosen = r.timed(lambda: seeds.mc_greedy_seeds(g, 3, objective="opinion", **SIM), model="greedy", k=3)
    r.add("opinion_spread", _value(g, chosen, "opinion"), "greedy", 3)
    return r.table()


def _fits(r: Report, runs: dict[str, str]) -> None:
    """Line through the seconds of a model over ``x``: slope and r squared."""
    rows = r.table().where("metric = 'seconds'")
    for name, x in runs.items():
        fit = rows.where(F.col("model") == name).agg(F.regr_slope("value", x).alias("a"), F.regr_r2("value", x).alias("r2")).first()
        r.add("slope", fit["a"], name)
        r.add("r2", fit["r2"], name)


def w10_time_opinion(s: SparkSession, d: str) -> DataFrame:
    """Seconds of the opinion score over path length and seed count, and the fit of a line."""
    r, g = Report(s, "w10"), _base(s, d)
    for length in range(1, 8):
        r.timed(lambda n=length: scores.opinion_walk_score(g, n), model="length", length=length)
    for k in (1, 3, 5):
        r.timed(lambda n=k: seeds.score_greedy_seeds(g, n, 1, True, "seed"), model="seeds", k=k, length=1)
    _fits(r, {"length": "l", "seeds": "k"})
    return r.table()


def w11_memory(s: SparkSession, d: str) -> DataFrame:
    """Memory over and above the arcs: peak execution memory of the walk score's stages (one row a node)
    against that of the pair state of the union score."""
    r = Report(s, "w11")
    for source in ("cop", "suc"):
        g = _base(s, d, source)
        r.add("graph_mb", plan_mb(g.edges), source)
        r.timed(lambda h=g: scores.walk_score(h, 3), model=f"walk {source}", length=3)
        r.timed(lambda h=g: scores.union_walk_score(h, 2), model=f"union {source}", length=2)
    return r.table()


def w13_background(s: SparkSession, d: str) -> DataFrame:
    """A hundred seeds (or as many as have a positive score) by the opinion score of length 1."""
    r, g = Report(s, "w13"), _base(s, d, "suc")
    chosen = r.timed(lambda: seeds.score_greedy_seeds(g, 100, 1, True, "seed"), model="oi", k=100, length=1)
    r.add("seeds", chosen.count(), "oi", 100, 1)
    r.add("opinion_spread", _value(g, chosen, "opinion"), "oi", 100, 1)
    return r.table()


def w14_length_oblivious(s: SparkSession, d: str) -> DataFrame:
    """Spread and seconds over path length under three first layers."""
    r = Report(s, "w14")
    for name, p in (("ic", "ic"), ("wc", "wc"), ("lt", "ic")):
        g = _base(s, d, "cop", p)
        scored = g.with_p("w") if name == "lt" else g
        for length in (1, 3):
            chosen = r.timed(lambda n=length, h=scored: seeds.score_greedy_seeds(h, 3, n, discount="seed"), model=name, k=3, length=length)
            r.add("spread", _value(g, chosen, model="lt" if name == "lt" else "ic"), name, 3, length)
    return r.table()


def w15_baselines(s: SparkSession, d: str) -> DataFrame:
    """Spread and seconds of the walk score against the competitors, and the deviation from the best."""
    r, g = Report(s, "w15"), _base(s, d, "suc", "wc")
    runs = {
        "walk": lambda: seeds.score_greedy_seeds(g, 3, 3, discount="seed"),
        "lazy": lambda: seeds.lazy_greedy_seeds(g, 3, **SIM),
        "rr": lambda: baselines.rr_seeds(g, 3, eps=0.2)[0],
        "rank": lambda: baselines.influence_rank_seeds(g, 3),
        "simpath": lambda: baselines.simpath_seeds(g, 3),
        "degree": lambda: seeds.degree_seeds(g, 3),
        "random": lambda: seeds.random_seeds(g, 3, mode=MODE),
    }
    found = {}
    for name, run in runs.items():
        found[name] = _value(g, r.timed(run, model=name, k=3))
        r.add("spread", found[name], name, 3)
    for name, v in found.items():
        r.add("deviation_pct", deviation_pct(v, max(found.values())), name, 3)
    return r.table()


def w16_growth(s: SparkSession, d: str) -> DataFrame:
    """Seconds over path length and seed count, and the fit of a line."""
    r, g = Report(s, "w16"), _base(s, d)
    for length in (1, 2, 4):
        r.timed(lambda n=length: scores.walk_score(g, n), model="length", length=length)
    for k in (1, 2, 4):
        r.timed(lambda n=k: seeds.score_greedy_seeds(g, n, 1, discount="seed"), model="seeds", k=k, length=1)
    _fits(r, {"length": "l", "seeds": "k"})
    return r.table()


def w17_memory_seeds(s: SparkSession, d: str) -> DataFrame:
    """Peak execution memory over the number of seeds, for the walk score and its competitors."""
    r, g = Report(s, "w17"), _base(s, d, "suc", "wc")
    r.add("graph_mb", plan_mb(g.edges))
    for k in (1, 2):
        r.timed(lambda n=k: seeds.score_greedy_seeds(g, n, 1, discount="seed"), model="walk", k=k, length=1)
        r.timed(lambda n=k: seeds.lazy_greedy_seeds(g, n, **SIM), model="lazy", k=k)
        r.timed(lambda n=k: baselines.rr_seeds(g, n, eps=0.2)[0], model="rr", k=k)
        r.timed(lambda n=k: baselines.influence_rank_seeds(g, n), model="rank", k=k)
        r.timed(lambda n=k: baselines.simpath_seeds(g, n, max_len=4), model="simpath", k=k)
    return r.table()


def _gain_table(s: SparkSession, d: str, name: str, sizes: dict[str, int], other: Callable[[InfluenceGraph, int], DataFrame]) -> DataFrame:
    """Seconds, peak memory and spread of the walk score of length 1 and a competitor, and the ratios."""
    r = Report(s, name)
    for source, k in sizes.items():
        g = _base(s, d, source, "wc")
        runs = {"walk": lambda h=g, n=k: seeds.score_greedy_seeds(h, n, 1, discount="seed"), "other": lambda h=g, n=k: other(h, n)}
        for model, run in runs.items():
            r.add("spread", _value(g, r.timed(run, model=f"{model} {source}", k=k, length=1)), f"{model} {source}", k, 1)
        for metric in ("seconds", "peak_mb"):
            r.add(f"gain_{metric}", gain(r.value(metric, f"other {source}", k), r.value(metric, f"walk {source}", k)), source, k, 1)
    return r.table()


def w18_reverse_sampling_gain(s: SparkSession, d: str) -> DataFrame:
    return _gain_table(s, d, "w18", {"suc": 3}, lambda g, k: baselines.rr_seeds(g, k, eps=0.2)[0])


def w19_lazy_greedy_gain(s: SparkSession, d: str) -> DataFrame:
    return _gain_table(s, d, "w19", {"suc": 3, "cop": 1}, lambda g, k: seeds.lazy_greedy_seeds(g, k, **SIM))


def graph_size(edges: DataFrame) -> tuple[int, int]:
    """Nodes with an arc, and arcs, in one pass that stores neither."""
    ends = edges.select(F.explode(F.array(F.col("u").cast("long"), F.col("v").cast("long"))).alias("id")).groupBy("id").agg(F.count(F.lit(1)).alias("c"))
    row = ends.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum("c"), F.lit(0)).alias("ends")).first()
    return row["n"], row["ends"] // 2


def similarity_size(rows: DataFrame) -> tuple[int, int]:
    """The same of the similarity graph, from the classes' degrees."""
    row = similar.degrees(rows).where("degree > 0").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.coalesce(F.sum(F.col("n") * F.col("degree")), F.lit(0)).alias("arcs")).first()
    return row["n"], row["arcs"]


def w20_datasets(s: SparkSession, d: str) -> DataFrame:
    r = Report(s, "w20")
    for name, size in (
        ("copurchase", lambda: graph_size(graphs.copurchase_edges(s, d))),
        ("succession", lambda: graph_size(graphs.succession_edges(s, d))),
        ("trade", lambda: graph_size(graphs.trade_edges(s, d, 2))),
        ("similarity", lambda: similarity_size(similar.features(s, d))),
        ("tree", lambda: graph_size(graphs.tree_edges(s, d))),
        ("order_dag", lambda: graph_size(graphs.order_dag_edges(s, d))),
        ("conversations", lambda: graph_size(graphs.conversation_edges(s, d))),
        ("copies", lambda: graph_size(graphs.copy_edges(s, d))),
        ("embedding", lambda: graph_size(graphs.embedding_edges(s, d))),
    ):
        n, m = size()
        r.add("nodes", n, name)
        r.add("arcs", m, name)
        r.add("avg_degree", m / n if n else 0.0, name)
    return r.table()


def w21_instances(s: SparkSession, d: str) -> DataFrame:
    """Uniform against normal opinions, averaged over three draws of all parameters."""
    r, g = Report(s, "w21"), _base(s, d, "suc")
    for name, draw in (("uniform", params.opinions_uniform), ("normal", params.opinions_normal)):
        values = []
        for instance in (1, 2, 3):
            h = params.interactions_uniform(draw(g, instance, mode=MODE), instance, mode=MODE).materialized()
            values.append(_value(h, seeds.score_greedy_seeds(h, 2, 2, True, "seed"), "opinion"))
        r.add("opinion_spread", sum(values) / 3, name, 2, 2)
    return r.table()


def w22_exactness(s: SparkSession, d: str) -> DataFrame:
    """Largest difference between walk and simple-path scores: none on a tree, positive with cycles."""
    r = Report(s, "w22")
    tree = graph(graphs.tree_edges(s, d)).materialized()
    cyclic = _base(s, d)
    for name, g in (("tree", tree), ("cyclic", cyclic)):
        both = scores.walk_score(g, 3).withColumnRenamed("score", "walk").join(scores.simple_path_score(g, 3), "id")
        r.add("max_difference", both.agg(F.max(F.abs(F.col("walk") - F.col("score")))).first()[0] or 0.0, name, length=3)
    agreement = errors.rank_agreement(scores.walk_score(cyclic, 3), scores.simple_path_score(cyclic, 3), 10).first()
    r.add("tau", agreement["tau"], "cyclic", length=3)
    return r.table()


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: f for k, f in globals().items() if k[0] == "w" and k[1:3].isdigit()}
