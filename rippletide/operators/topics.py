"""Topic subgraphs from an event stream, and estimation of opinions and interactions."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rippletide.operators.graphs import InfluenceGraph
from rippletide.plans.storage import stored
from rippletide.sources.tables import table


def prob_to_opinion(p: Column) -> Column:
    """A probability of the positive class to an opinion in [-1, 1]."""
    return 2 * p - 1


def post_opinion(kind: Column, value: Column) -> Column:
    """Two-stage reading of an event: views are neutral; for the others the strength
    value / (value + 50) gives the positive class's probability, mirrored for errors."""
    strength = value / (value + 50)
    p = F.when(kind == "error", (1 - strength) / 2).otherwise((1 + strength) / 2)
    return F.when(kind == "view", F.lit(0.0)).otherwise(prob_to_opinion(p))


def topic_posts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(event_id, user_id, ts, topic, opinion) of the events that carry a topic."""
    e = table(spark, sf_dir, "events")
    return e.select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"), F.get_json_object("props", "$.k").cast("int").alias("topic"), post_opinion(F.col("event_type"), F.col("value")).alias("opinion")).where("topic is not null")


def _gaps(posts: DataFrame) -> DataFrame:
    order = Window.partitionBy("topic").orderBy("ts", "event_id")
    seconds = F.unix_micros("ts") / 1_000_000.0
    return posts.withColumn("gap", seconds - F.lag(seconds).over(order))


def gap_threshold(posts: DataFrame, c: float = 2.0) -> DataFrame:
    """(topic, threshold): mean gap between a topic's posts plus c standard deviations."""
    return _gaps(posts).groupBy("topic").agg((F.avg("gap") + c * F.coalesce(F.stddev_pop("gap"), F.lit(0.0))).alias("threshold"))


def epochs_by_post(posts: DataFrame, c: float = 2.0) -> DataFrame:
    """posts with ``epoch``: a topic's subgraph ends where no post came for longer than the threshold."""
    cut = _gaps(posts).join(gap_threshold(posts, c), "topic").withColumn("cut", F.coalesce((F.col("gap") > F.col("threshold")).cast("int"), F.lit(0)))
    upto = Window.partitionBy("topic").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return cut.withColumn("epoch", F.sum("cut").over(upto)).select("event_id", "user_id", "ts", "topic", "opinion", "epoch")


def _fold(key, frames: Iterator[pd.DataFrame] | pd.DataFrame) -> pd.DataFrame:
    """One topic in time order; the epoch ends once no node without predecessors joined for longer than
    the threshold."""
    df = frames.sort_values(["ts", "event_id"])
    epoch, last_seed, members, out = 0, None, set(), []
    for event_id, user, ts, sources, limit in zip(df["event_id"], df["user_id"], df["ts"], df["sources"], df["threshold"], strict=True):
        now = ts.timestamp()
        if last_seed is not None and now - last_seed > limit:
            epoch, members, last_seed = epoch + 1, set(), None
        if user not in members:
            reached = any(s in members for s in (sources if sources is not None else ()))
            members.add(user)
            if not reached or last_seed is None:
                last_seed = now
        out.append((event_id, epoch))
    return pd.DataFrame(out, columns=["event_id", "epoch"])


def epochs_by_seed(posts: DataFrame, background: DataFrame, c: float = 2.0) -> DataFrame:
    """posts with ``epoch``, cut where no new seed node came for longer than the threshold. Whether a user
    is a seed depends on who is in the subgraph already, so each topic is folded in order; a topic must
    fit a task (the streaming form keeps only its state)."""
    sources = background.groupBy(F.col("v").alias("user_id")).agg(F.collect_list("u").alias("sources"))
    rows = posts.join(sources, "user_id", "left").join(gap_threshold(posts, c), "topic").select("topic", "event_id", "user_id", "ts", "sources", "threshold")
    cut = rows.groupBy("topic").applyInPandas(_fold, "event_id long, epoch long")
    return posts.join(cut, "event_id")


def project_graph(edges: DataFrame, users: DataFrame) -> DataFrame:
    """The background arcs between users (user_id) who posted on a topic."""
    u = users.select("user_id").distinct()
    return edges.join(u.withColumnRenamed("user_id", "u"), "u", "left_semi").join(u.withColumnRenamed("user_id", "v"), "v", "left_semi")


def topic_members(epochs: DataFrame) -> DataFrame:
    """(topic, epoch, user_id, first_ts, opinion): a user's first post and mean opinion in an epoch."""
    return epochs.groupBy("topic", "epoch", "user_id").agg(F.min("ts").alias("first_ts"), F.avg("opinion").alias("opinion"))


def topic_edges(members: DataFrame, background: DataFrame, time_respecting: bool = False) -> DataFrame:
    """(topic, epoch, u, v): background arcs between members of one epoch."""
    a = members.select("topic", "epoch", F.col("user_id").alias("u"), F.col("first_ts").alias("tu"))
    b = members.select("topic", "epoch", F.col("user_id").alias("v"), F.col("first_ts").alias("tv"))
    rows = a.join(background.select("u", "v"), "u").join(b, ["topic", "epoch", "v"])
    return (rows.where("tu < tv") if time_respecting else rows).select("topic", "epoch", "u", "v")


def originators(members: DataFrame, edges: DataFrame) -> DataFrame:
    """(topic, epoch, user_id) of members without an in-arc."""
    return members.select("topic", "epoch", "user_id").join(edges.select("topic", "epoch", F.col("v").alias("user_id")).distinct(), ["topic", "epoch", "user_id"], "left_anti")


def top_topics(posts: DataFrame, n: int = 100, min_posts: int = 0) -> DataFrame:
    return posts.groupBy("topic").agg(F.count(F.lit(1)).alias("posts")).where(F.col("posts") >= min_posts).orderBy(F.desc("posts"), "topic").limit(n)


def true_opinion(posts: DataFrame) -> DataFrame:
    return posts.groupBy("topic", "user_id").agg(F.avg("opinion").alias("opinion"))


def estimate_opinion(posts: DataFrame, horizon_days: float = 10.0, decade: int = 10) -> DataFrame:
    """(topic, user_id, truth, estimate): a user's opinion on a topic as the weighted mean of own opinions
    on related topics (same decade of topic ids) before the first own post on it, by recency
    exp(-age / horizon). Users without such a past get no row."""
    own = posts.groupBy("topic", "user_id").agg(F.avg("opinion").alias("truth"), F.min("ts").alias("first_ts"))
    past = posts.select("user_id", F.col("topic").alias("other"), F.col("ts").alias("past_ts"), F.col("opinion").alias("past"), F.floor(F.col("topic") / decade).alias("family"))
    rows = own.withColumn("family", F.floor(F.col("topic") / decade)).join(past, ["user_id", "family"]).where((F.col("other") != F.col("topic")) & (F.col("past_ts") < F.col("first_ts")))
    age = (F.unix_micros("first_ts") - F.unix_micros("past_ts")) / (86_400_000_000.0 * horizon_days)
    w = F.exp(-age)
    return rows.groupBy("topic", "user_id").agg(F.max("truth").alias("truth"), (F.sum(w * F.col("past")) / F.sum(w)).alias("estimate"))


def estimate_interaction(members: DataFrame, background: DataFrame, default: float = 0.5) -> DataFrame:
    """(u, v, phi, times): share of the epochs both were in, over all topics, in which their opinions have
    one sign; ``default`` for arcs without a common epoch."""
    a = members.select("topic", "epoch", F.col("user_id").alias("u"), F.col("opinion").alias("ou"))
    b = members.select("topic", "epoch", F.col("user_id").alias("v"), F.col("opinion").alias("ov"))
    both = background.select("u", "v").join(a, "u").join(b, ["topic", "epoch", "v"])
    agree = both.groupBy("u", "v").agg(F.avg((F.signum("ou") == F.signum("ov")).cast("double")).alias("phi"), F.count(F.lit(1)).alias("times"))
    return background.select("u", "v").join(agree, ["u", "v"], "left").select("u", "v", F.coalesce("phi", F.lit(float(default))).alias("phi"), F.coalesce("times", F.lit(0)).alias("times"))


def nrmse(rows: DataFrame, estimate: str, truth: str, norm: str = "range", by: list[str] | None = None) -> DataFrame:
    """Root-mean-square error over the range of the truth (or over 2, the opinions' span)."""
    err = F.sqrt(F.avg((F.col(estimate) - F.col(truth)) ** 2))
    span = F.max(truth) - F.min(truth) if norm == "range" else F.lit(2.0)
    return rows.groupBy(*(by or [])).agg(F.try_divide(err, span).alias("nrmse"), F.count(F.lit(1)).alias("n"))


def ground_truth_spread(members: DataFrame, origin: DataFrame) -> DataFrame:
    """(topic, epoch, spread): sum of the true opinions of members that are no originators."""
    rest = members.join(origin, ["topic", "epoch", "user_id"], "left_anti")
    sums = rest.groupBy("topic", "epoch").agg(F.sum("opinion").alias("s"))
    return members.select("topic", "epoch").distinct().join(sums, ["topic", "epoch"], "left").select("topic", "epoch", F.coalesce("s", F.lit(0.0)).alias("spread"))


def model_spreads(members: DataFrame, edges: DataFrame, origin: DataFrame, opinions: DataFrame, phi: DataFrame, worlds: int, seed: int = 1, mode: str = "xxhash") -> DataFrame:
    """(topic, epoch, model, spread): expected opinion spread of each subgraph's originators under the
    opinion-interaction model, the same without interactions (``oc``), and counted without opinions
    (``ic``). All subgraphs run as one cascade, whose activations are those of all three models: their nodes
    get ids of their own."""
    from rippletide.operators import diffusion, params

    node = F.xxhash64("topic", "epoch", "user_id")
    nodes = members.join(opinions, ["topic", "user_id"], "left").select(node.alias("id"), F.coalesce("estimate", F.lit(0.0)).alias("o"), F.lit(0.5).alias("theta"), "topic", "epoch")
    arcs = edges.join(phi.select("u", "v", "phi"), ["u", "v"], "left").select(F.xxhash64("topic", "epoch", "u").alias("u"), F.xxhash64("topic", "epoch", "v").alias("v"), F.lit(0.1).alias("p"), F.lit(0.0).alias("w"), F.coalesce("phi", F.lit(0.5)).alias("phi"))
    g = params.assign_wc(InfluenceGraph(nodes.select("id", "o", "theta"), arcs)).materialized()
    seeds = origin.select(node.alias("id"))
    where = nodes.select("id", "topic", "epoch")
    act = diffusion.cascade_ic(g, seeds, worlds, seed, mode=mode, plain=True)
    sums = {"oi": F.sum("o_final"), "oc": F.sum("o_plain"), "ic": F.sum(F.lit(1.0))}
    found = act.where("step > 0").join(where, "id").groupBy("topic", "epoch").agg(*[(x / worlds).alias(k) for k, x in sums.items()])
    return stored(found, "model_spreads").unpivot(["topic", "epoch"], list(sums), "model", "spread")
