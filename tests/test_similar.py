"""The similarity graph by classes against all pairs."""

import pytest
from pyspark.sql import functions as F

from rippletide.operators import churn, graphs, similar
from rippletide.plans.cost import Meter
from rippletide.plans.storage import stored

KINDS = "id long, f1 int, f2 string, f3 long, f4 long, label double"


def people(spark, n, kinds=3):
    """Some with a null feature, and two in the same class as many others."""
    rows = [(i, i % kinds, "abc"[i // 3 % kinds % 3], i // 7 % 2, i // 11 % 2 if i % 13 else None, 1.0 if i % 5 else -1.0) for i in range(n)]
    return rows, spark.createDataFrame(rows, KINDS)


def brute(rows, least=3):
    same = lambda a, b: None if None in a[1:5] + b[1:5] else sum(x == y for x, y in zip(a[1:5], b[1:5], strict=True))
    return {(a[0], b[0], same(a, b) / 4) for a in rows for b in rows if a[0] != b[0] and (same(a, b) or 0) >= least}


@pytest.mark.parametrize("least", [3, 4])
def test_arcs_equal_all_pairs(spark, monkeypatch, least):
    monkeypatch.setattr(similar, "LIST", 4)
    monkeypatch.setattr(similar, "SHARE", 8)
    rows, df = people(spark, 90)
    got = [tuple(r) for r in similar.arcs(df, least).collect()]
    assert len(got) == len(set(got)) and set(got) == brute(rows, least)


def one_class(spark, monkeypatch, n):
    df = spark.range(n).select("id", F.lit(1).alias("f1"), F.lit("a").alias("f2"), F.lit(1).cast("long").alias("f3"), F.lit(1).cast("long").alias("f4"))
    tables = {"orders": spark.createDataFrame([(0,)], "o_custkey long").where("false"), "customer": df.select(F.col("id").alias("c_custkey"), F.col("f1").alias("c_nationkey"), F.col("f2").alias("c_mktsegment"), F.lit(1500.0).alias("c_acctbal"))}
    for module in (similar, graphs):
        monkeypatch.setattr(module, "table", lambda s, d, name: tables[name])
    return df


def test_arcs_of_a_large_class_pass_no_exchange(spark, monkeypatch):
    one_class(spark, monkeypatch, 400)
    with Meter(spark) as meter:
        arcs = stored(graphs.similarity_edges(spark, ""), "arcs")
    assert arcs.count() == 400 * 399
    assert meter.rows < 10_000


def test_propagation_by_class_equals_propagation_along_arcs(spark):
    rows, df = people(spark, 90)
    g = graphs.graph(similar.arcs(df.drop("label")), df.select("id"))
    for kw in ({"rounds": 3}, {"max_iter": 10}):
        want = {r["id"]: r["value"] for r in churn.propagate_labels(g, df.select("id", "label"), **kw).collect()}
        got = {r["id"]: r["value"] for r in similar.propagate(df, **kw).collect()}
        assert got.keys() == want.keys() and all(got[k] == pytest.approx(want[k], abs=1e-12) for k in want)


def test_registered_propagation_makes_no_arcs(spark, monkeypatch):
    from rippletide import workloads

    rows = one_class(spark, monkeypatch, 400)
    monkeypatch.setattr(churn, "churn_labels", lambda *_: rows.select("id", F.when(F.col("id") < 100, -1).otherwise(1).alias("label")))
    with Meter(spark) as meter:
        got = {r["id"]: r["value"] for r in workloads.REGISTRY["label_propagation_t5"](spark, "").collect()}
    assert len(got) == 400 and got[0] < 0 < got[399]
    assert meter.rows < 10_000


def test_sizes_of_data_sets_store_no_arcs(spark, monkeypatch):
    from rippletide import reports

    rows, df = people(spark, 90)
    arcs = brute(rows)
    ends = {u for u, _, _ in arcs}
    assert reports.similarity_size(df.drop("label")) == (len(ends), len(arcs)) == reports.graph_size(similar.arcs(df.drop("label")))
    assert reports.graph_size(spark.createDataFrame([], "u long, v long")) == (0, 0)
    monkeypatch.setattr(graphs.InfluenceGraph, "materialized", lambda *_: pytest.fail("stored"))
    sizes = {(r["model"], r["metric"]): r["value"] for r in reports.w20_datasets(spark, "/root/testdata/sf0.001").collect()}
    want = graphs.graph(graphs.similarity_edges(spark, "/root/testdata/sf0.001").select("u", "v"))
    assert sizes["similarity", "nodes"] == want.nodes.count() and sizes["similarity", "arcs"] == want.edges.count()


@pytest.mark.parametrize("bound", [200_000, 0])
def test_scores_and_cascades_by_class_equal_those_along_arcs(spark, monkeypatch, bound):
    from rippletide.operators import diffusion, params, seeds

    monkeypatch.setattr(similar, "LIST", 4)
    monkeypatch.setattr(similar, "BROADCAST_ROWS", bound)
    rows, df = people(spark, 60)
    df = df.drop("label").withColumn("o", F.sin(F.col("id")))
    g = similar.cascade_graph(df)
    plain = params.interactions_uniform(params.assign_wc(graphs.graph(similar.arcs(df.drop("o")), df.select("id", "o")))).materialized()
    start = spark.createDataFrame([(0, 3), (0, 17), (1, 40)], "run long, id long")
    acts = [sorted((r["run"], r["world"], r["id"], r["step"], r["parent"] or -1, round(r["o_final"], 9)) for r in diffusion.cascade_ic(h, start, 4).collect()) for h in (g, plain)]
    assert acts[0] == acts[1] and max(a[3] for a in acts[0]) > 1
    if bound:
        for opinion, interaction in ((True, True), (True, False)):
            h = plain if interaction else graphs.InfluenceGraph(plain.nodes, plain.edges.withColumn("phi", F.lit(1.0)))
            want = [(r["id"], pytest.approx(r["score"], abs=1e-9)) for r in seeds.score_greedy_seeds(h, 3, 2, opinion, "seed").collect()]
            assert [(r["id"], r["score"]) for r in similar.score_seeds(g, 3, 2, opinion, interaction).collect()] == want


def test_churn_report_stores_no_arcs(spark, monkeypatch):
    from rippletide import reports

    monkeypatch.setattr(graphs, "by_target", lambda *_: pytest.fail("stored arcs"))
    assert {r["model"]: round(r["value"], 6) for r in reports.w07_churn(spark, "/root/testdata/sf0.001").collect()} == {"oi": 4.159148, "oc": 3.596648, "ic": 0.923697}


def test_draws_of_pairs_equal_those_of_the_text():
    import hashlib

    import numpy as np

    from rippletide.functions.rng import pair_draws

    u, v = np.array([0, 7, 12, 999999, -5, 2**63 - 1, -(2**63)]), np.array([3, 10**12, -44, 123456, -(2**63)])
    i, j = (x.ravel() for x in np.meshgrid(np.arange(len(u)), np.arange(len(v))))
    want = [int(hashlib.md5(f"phi|1|{a}|{b}".encode()).hexdigest()[:8], 16) / 2**32 for a, b in zip(u[i], v[j], strict=True)]
    assert pair_draws("phi|1", u, v, i, j).tolist() == want


def test_scores_by_md5_equal_those_along_arcs_and_pair_the_last_step_for_leaders_only(spark, monkeypatch):
    from rippletide.operators import params, seeds

    monkeypatch.setattr(similar, "LIST", 4)
    monkeypatch.setattr(similar, "PAIRS", 50)
    rows, df = people(spark, 60)
    alone = spark.createDataFrame([(1000, 77, "z", 77, 77, 1.0)], KINDS)
    df = df.union(alone).drop("label").withColumn("o", F.sin(F.col("id")))
    g = similar.cascade_graph(df, mode="md5")
    plain = params.interactions_uniform(params.assign_wc(graphs.graph(similar.arcs(df.drop("o")), df.select("id", "o"))), mode="md5").materialized()
    tails = []
    turned = similar._turned_sums
    monkeypatch.setattr(similar, "_turned_sums", lambda g, x, ids=None: tails.append(60 if ids is None else ids.count()) or turned(g, x, ids))
    want = [(r["id"], pytest.approx(r["score"], abs=1e-9)) for r in seeds.score_greedy_seeds(plain, 2, 2, True, "seed").collect()]
    assert [(r["id"], r["score"]) for r in similar.score_seeds(g, 2, 2, True).collect()] == want
    assert min(tails) < 30
