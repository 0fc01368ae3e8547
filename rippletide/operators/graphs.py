"""The influence graph and its builders over the given tables."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rippletide.plans.storage import by_target, stored
from rippletide.sources.tables import table


@dataclass(frozen=True)
class InfluenceGraph:
    """nodes (id, o, theta) and directed edges (u, v, p, w, phi)."""

    nodes: DataFrame
    edges: DataFrame

    def materialized(self) -> InfluenceGraph:
        """Stored once, arcs laid out by head, for plans that scan them many times."""
        return InfluenceGraph(stored(self.nodes, "nodes"), by_target(self.edges))

    def arcs_from(self, front: DataFrame, n: int) -> DataFrame:
        """The arcs, or at least those that start in ``front`` (u), a table of ``n`` rows."""
        return self.edges

    def with_p(self, column: str | Column) -> InfluenceGraph:
        return replace(self, edges=self.edges.withColumn("p", F.col(column) if isinstance(column, str) else column))

    def without(self, removed: DataFrame) -> InfluenceGraph:
        """Arcs that start or end in ``removed`` (id) go, and so do the nodes."""
        gone = removed.select("id")
        edges = self.edges.join(gone.withColumnRenamed("id", "u"), "u", "left_anti").join(gone.withColumnRenamed("id", "v"), "v", "left_anti")
        return InfluenceGraph(self.nodes.join(gone, "id", "left_anti"), edges.select("u", "v", "p", "w", "phi"))

    def induced(self, users: DataFrame) -> InfluenceGraph:
        """The subgraph on ``users`` (id)."""
        keep = users.select("id").distinct()
        edges = self.edges.join(keep.withColumnRenamed("id", "u"), "u", "left_semi").join(keep.withColumnRenamed("id", "v"), "v", "left_semi")
        return InfluenceGraph(self.nodes.join(keep, "id", "left_semi"), edges.select("u", "v", "p", "w", "phi"))


def graph(edges: DataFrame, nodes: DataFrame | None = None) -> InfluenceGraph:
    """Fill in what is missing: nodes are the endpoints, o = 0, theta = 0.5, p = 0.1, w = 0, phi = 0.5."""
    ends = edges.select(F.col("u").alias("id")).union(edges.select("v")).distinct()
    nodes = ends if nodes is None else nodes
    value = lambda df, c, d: F.col(c).cast("double").alias(c) if c in df.columns else F.lit(float(d)).alias(c)
    return InfluenceGraph(
        nodes.select(F.col("id").cast("long").alias("id"), value(nodes, "o", 0), value(nodes, "theta", 0.5)),
        edges.select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v"), value(edges, "p", 0.1), value(edges, "w", 0), value(edges, "phi", 0.5)),
    )


def normalize(g: InfluenceGraph, merge: str = "max") -> InfluenceGraph:
    """No nulls, no self-loops, one arc a pair (largest p, or 1 - prod(1 - p)), values in range,
    endpoints among the nodes."""
    merged = F.max("p") if merge == "max" else 1 - F.product(1 - F.col("p"))
    bound = lambda c, lo: F.greatest(F.lit(float(lo)), F.least(F.lit(1.0), F.col(c))).alias(c)
    edges = g.edges.where("u is not null and v is not null and u <> v and p is not null").groupBy("u", "v").agg(merged.alias("p"), F.max("w").alias("w"), F.max("phi").alias("phi"))
    nodes = g.nodes.where("id is not null").groupBy("id").agg(F.coalesce(F.max("o"), F.lit(0.0)).alias("o"), F.coalesce(F.max("theta"), F.lit(0.5)).alias("theta"))
    ends = edges.select(F.col("u").alias("id")).union(edges.select("v")).distinct()
    nodes = ends.join(nodes, "id", "full").select("id", F.coalesce("o", F.lit(0.0)).alias("o"), F.coalesce("theta", F.lit(0.5)).alias("theta"))
    return InfluenceGraph(nodes.select("id", bound("o", -1), bound("theta", 0)), edges.select("u", "v", bound("p", 0), bound("w", 0), bound("phi", 0)))


def violations(g: InfluenceGraph) -> DataFrame:
    """(rule, n) of rows that break a rule of ``normalize``."""
    e, n = g.edges, g.nodes
    ends = e.select(F.col("u").alias("id")).union(e.select("v"))
    parts = [
        ("self_loop", e.where("u = v")),
        ("null", e.where("u is null or v is null or p is null")),
        ("range", e.where("p < 0 or p > 1 or w < 0 or w > 1 or phi < 0 or phi > 1")),
        ("opinion", n.where("o is null or o < -1 or o > 1")),
        ("repeated", e.groupBy("u", "v").count().where("count > 1")),
        ("unknown_end", ends.join(n, "id", "left_anti")),
    ]
    out = None
    for name, rows in parts:
        one = rows.agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("rule"), "n")
        out = one if out is None else out.union(one)
    return out


def symmetrize(edges: DataFrame) -> DataFrame:
    """Each undirected edge as two arcs, each once."""
    rest = [c for c in edges.columns if c not in ("u", "v")]
    return edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v"), *rest)).distinct()


def toy_graph(spark: SparkSession) -> InfluenceGraph:
    """The worked example: nodes 1..4 stand for A..D. Fixed values."""
    nodes = spark.createDataFrame([(1, 0.8, 0.5), (2, 0.0, 0.5), (3, 0.6, 0.5), (4, -0.3, 0.5)], "id long, o double, theta double")
    edges = spark.createDataFrame([(2, 1, 0.1, 1.0, 0.7), (2, 3, 0.1, 1.0, 0.8), (1, 4, 0.8, 0.5, 0.9), (3, 4, 0.9, 0.5, 0.1)], "u long, v long, p double, w double, phi double")
    return InfluenceGraph(nodes, edges)


def two_layer_graph(spark: SparkSession, nx: int) -> InfluenceGraph:
    """Sources 1..nx of opinion 1, each with two own targets of opinion 0; p = 1, and phi is 0 on the
    last source's arcs only: adding seeds makes the spread fall and rise again."""
    x = spark.range(1, nx + 1).select(F.col("id").alias("u"))
    edges = x.select("u", F.explode(F.array(F.col("u") * 2 - 1, F.col("u") * 2)).alias("k")).select("u", (F.col("k") + 1_000_000).alias("v"), F.lit(1.0).alias("p"), F.lit(1.0).alias("w"), F.when(F.col("u") == nx, 0.0).otherwise(1.0).alias("phi"))
    nodes = x.select(F.col("u").alias("id"), F.lit(1.0).alias("o"), F.lit(0.5).alias("theta")).union(edges.select("v", F.lit(0.0), F.lit(0.5)))
    return InfluenceGraph(nodes, edges)


def order_layer_graph(spark: SparkSession, sf_dir: str) -> InfluenceGraph:
    """The two layers on the tables: customers of opinion 1, their own orders (from 10**12 on) of opinion 0;
    p = 1, and phi is 0 on the arcs of the last customer only."""
    o = table(spark, sf_dir, "orders").where("o_custkey is not null").select(F.col("o_custkey").alias("u"), (F.col("o_orderkey") + 10**12).alias("v"))
    last = F.broadcast(o.agg(F.max("u").alias("last")))
    edges = o.join(last).select("u", "v", F.lit(1.0).alias("p"), F.lit(1.0).alias("w"), F.when(F.col("u") == F.col("last"), 0.0).otherwise(1.0).alias("phi"))
    nodes = o.select(F.col("u").alias("id"), F.lit(1.0).alias("o"), F.lit(0.5).alias("theta")).distinct().union(o.select("v", F.lit(0.0), F.lit(0.5)))
    return InfluenceGraph(nodes, edges)


def set_cover_graph(spark: SparkSession, n: int, sets: list[list[int]]) -> InfluenceGraph:
    """Hardness instance: sets (ids 1..), elements (1001..), m + n - 2 middle nodes (2001..) that every
    element reaches, and a sink (3001) that every middle node reaches; p = phi = 1. A cover among the
    sets gives the spread 1/(2n), anything less at most 0 (seeds from the first layer only)."""
    m = len(sets)
    middle = range(2001, 2001 + m + n - 2)
    opinions = [(1 + i, 0.0) for i in range(m)] + [(1001 + j, 1 / n) for j in range(n)] + [(z, -1 / (2 * n)) for z in middle] + [(3001, -1 + 1 / n)]
    arcs = [(1 + i, 1001 + j) for i, s in enumerate(sets) for j in s] + [(1001 + j, z) for j in range(n) for z in middle] + [(z, 3001) for z in middle]
    nodes = spark.createDataFrame([(i, float(o), 1.0) for i, o in opinions], "id long, o double, theta double")
    edges = spark.createDataFrame([(u, v, 1.0, 1.0, 1.0) for u, v in arcs], "u long, v long, p double, w double, phi double")
    return InfluenceGraph(nodes, edges)


def copurchase_edges(spark: SparkSession, sf_dir: str, min_orders: int = 2) -> DataFrame:
    """Parts sharing at least ``min_orders`` orders, both ways; pairs are distinct before counting."""
    pairs = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    a, b = pairs.select("l_orderkey", F.col("l_partkey").alias("u")), pairs.select("l_orderkey", F.col("l_partkey").alias("v"))
    half = a.join(b, "l_orderkey").where("u < v").groupBy("u", "v").agg(F.count(F.lit(1)).alias("orders")).where(F.col("orders") >= min_orders)
    return half.select("u", "v", "orders").union(half.select("v", "u", "orders"))


def succession_edges(spark: SparkSession, sf_dir: str, min_weight: int = 2) -> DataFrame:
    """user -> next user in the stream of one event type. The stream is cut by day, and each day's
    first event takes its predecessor from the last event before that day, so no task orders a whole
    type."""
    e = table(spark, sf_dir, "events").select("event_type", "ts", "event_id", "user_id").withColumn("day", F.to_date("ts"))
    within = Window.partitionBy("event_type", "day").orderBy("ts", "event_id")
    last = e.groupBy("event_type", "day").agg(F.max_by("user_id", F.struct("ts", "event_id")).alias("last_user"))
    days = last.withColumn("before", F.lag("last_user").over(Window.partitionBy("event_type").orderBy("day"))).select("event_type", "day", "before")
    rows = e.withColumn("prev", F.lag("user_id").over(within)).join(days, ["event_type", "day"])
    pairs = rows.select(F.coalesce("prev", "before").alias("u"), F.col("user_id").alias("v")).where("u is not null and u <> v")
    return pairs.groupBy("u", "v").agg(F.count(F.lit(1)).alias("weight")).where(F.col("weight") >= min_weight)


def trade_edges(spark: SparkSession, sf_dir: str, min_lines: int = 1) -> DataFrame:
    """customer -> supplier (suppliers from 10**12 on) through their order lines."""
    o = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    li = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    rows = li.join(o, F.col("l_orderkey") == F.col("o_orderkey"))
    return rows.groupBy(F.col("o_custkey").alias("u"), (F.col("l_suppkey") + 10**12).alias("v")).agg(F.count(F.lit(1)).alias("lines")).where(F.col("lines") >= min_lines)


def tree_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """region -> nation -> customer -> order, kinds offset by 10**12."""
    k = 10**12
    n = table(spark, sf_dir, "nation").select(F.col("n_regionkey").cast("long").alias("u"), (F.col("n_nationkey") + k).alias("v"))
    c = table(spark, sf_dir, "customer").select((F.col("c_nationkey") + k).alias("u"), (F.col("c_custkey") + 2 * k).alias("v"))
    o = table(spark, sf_dir, "orders").select((F.col("o_custkey") + 2 * k).alias("u"), (F.col("o_orderkey") + 3 * k).alias("v"))
    return n.union(c).union(o)


def order_dag_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """customer -> order -> part: a DAG whose paths meet again."""
    k = 10**12
    o = table(spark, sf_dir, "orders").select((F.col("o_custkey") + 2 * k).alias("u"), (F.col("o_orderkey") + 3 * k).alias("v"))
    li = table(spark, sf_dir, "lineitem").select((F.col("l_orderkey") + 3 * k).alias("u"), (F.col("l_partkey") + 4 * k).alias("v")).distinct()
    return o.union(li)


def nation_part_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(u, v, t): how many paths nation -> customer -> order -> part lead from a nation to a part."""
    c, o = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey"), table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    li = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    rows = li.join(o.join(c, F.col("o_custkey") == F.col("c_custkey")), F.col("l_orderkey") == F.col("o_orderkey"))
    return rows.groupBy(F.col("c_nationkey").alias("u"), F.col("l_partkey").alias("v")).agg(F.count(F.lit(1)).alias("t"))


def conversation_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each turn to the next of its conversation: disjoint paths. Id = conversation * 10**6 + turn."""
    c = table(spark, sf_dir, "conversations").select("conv_id", "turn")
    nxt = F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn"))
    of = lambda t: F.col("conv_id") * 1_000_000 + F.col(t)
    return c.withColumn("next", nxt).where("next is not null").select(of("turn").alias("u"), of("next").alias("v"))


def similarity_edges(spark: SparkSession, sf_dir: str, threshold: int = 3) -> DataFrame:
    """Customers that agree on at least ``threshold`` (3 or 4) of nation, segment, balance bin and
    order-count bin; p is the share they agree on. Arcs come from lists of equal customers (``similar``)."""
    from rippletide.operators import similar

    return similar.arcs(similar.features(spark, sf_dir), threshold)


def embedding_edges(spark: SparkSession, sf_dir: str, min_cos: float = 0.3, block: int = 2048) -> DataFrame:
    """Vectors with a cosine of at least ``min_cos``, p the cosine. Vectors are compared block by block:
    a scan carries at most ``block`` of them, so its memory does not grow with the table."""
    rows = table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("x"))
    blocks = max(1, -(-rows.count() // block))
    out = None
    for b in range(blocks):
        part = rows.where(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)) == b).toArrow()
        ids = part["vec_id"].to_numpy()
        y = np.array(part["x"].to_pylist(), float)
        y /= np.maximum(np.linalg.norm(y, axis=1, keepdims=True), 1e-300)
        one = rows.mapInArrow(lambda it, ids=ids, y=y: _cosines(it, ids, y, min_cos), "u long, v long, p double")
        out = one if out is None else out.union(one)
    return out


def _cosines(batches: Iterator[pa.RecordBatch], ids: np.ndarray, y: np.ndarray, least: float) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        mine = batch.column(0).to_numpy()
        x = np.array(batch.column(1).to_pylist(), float)
        x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300)
        c = x @ y.T
        i, j = np.nonzero((c >= least) & (mine[:, None] != ids[None, :]))
        yield pa.RecordBatch.from_arrays([pa.array(mine[i]), pa.array(ids[j]), pa.array(np.minimum(c[i, j], 1.0))], names=["u", "v", "p"])


def link_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """page -> linked path, with how often it links there."""
    hrefs = F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))
    return table(spark, sf_dir, "pages").select("page_id", F.explode(hrefs).alias("href")).groupBy("page_id", "href").agg(F.count(F.lit(1)).alias("links"))


def copy_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exact copies of documents as a star around the smallest id, both ways."""
    d = table(spark, sf_dir, "documents").select("doc_id", F.md5(F.col("text").cast("binary")).alias("h"))
    hub = d.groupBy("h").agg(F.min("doc_id").alias("hub"), F.max("doc_id").alias("top")).where("top > hub")
    half = d.join(hub, "h").where("doc_id <> hub").select(F.col("hub").alias("u"), F.col("doc_id").alias("v"))
    return half.union(half.select("v", "u"))


def profile(g: InfluenceGraph, hops: int = 4) -> DataFrame:
    """n, m, average degree, and the pairs within 1..hops steps by exact neighbourhood growth."""
    reach, sizes = g.edges.select("u", "v").distinct(), []
    step = reach
    for h in range(1, hops + 1):
        if h > 1:
            step = reach.alias("r").join(g.edges.alias("e"), F.col("r.v") == F.col("e.u")).select(F.col("r.u").alias("u"), F.col("e.v").alias("v")).where("u <> v").union(reach).distinct()
            reach = stored(step, "reach")
        sizes.append(reach.agg(F.count(F.lit(1)).alias("n")).select(F.lit(h).alias("hops"), "n"))
    out = sizes[0]
    for s in sizes[1:]:
        out = out.union(s)
    base = g.nodes.agg(F.count(F.lit(1)).alias("nodes")).join(g.edges.agg(F.count(F.lit(1)).alias("arcs")))
    return out.join(F.broadcast(base)).select("nodes", "arcs", F.round(F.col("arcs") / F.col("nodes"), 6).alias("avg_degree"), "hops", F.col("n").alias("pairs"))


def profile_sketch(g: InfluenceGraph, share: float = 0.9) -> DataFrame:
    """Approximate 90-percentile diameter: every node's neighbourhood as a mergeable distinct-count
    sketch, united along arcs once a hop until the pair count stays the same; interpolated where it passes
    ``share``."""
    state = g.nodes.select("id", "id").toDF("id", "k").groupBy("id").agg(F.hll_sketch_agg("k", F.lit(10)).alias("s"))
    totals = []
    while len(totals) < 2 or totals[-1] != totals[-2]:
        state = stored(state, "sketch")
        totals.append(state.agg(F.sum(F.hll_sketch_estimate("s"))).first()[0] or 0)
        along = g.edges.join(state, F.col("v") == F.col("id")).select(F.col("u").alias("id"), "s")
        state = state.union(along).groupBy("id").agg(F.hll_union_agg("s").alias("s"))
    goal = share * totals[-1]
    at = next((h for h in range(1, len(totals)) if totals[h] >= goal), len(totals) - 1)
    gap = totals[at] - totals[at - 1]
    diameter = at - 1 + (goal - totals[at - 1]) / gap if gap else float(at)
    return g.edges.sparkSession.createDataFrame([(float(diameter), int(totals[-1]))], "diameter90 double, pairs long")
