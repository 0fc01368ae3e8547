"""Golden values, invariants and edge cases of scores, diffusion and seed selection."""

import pytest
from pyspark.sql import functions as F

from rippletide import reports, workloads
from rippletide.operators import baselines, diffusion, errors, graphs, params, scores, seeds, spread
from rippletide.operators.graphs import graph


def values(df, key="id", value="score"):
    return {r[key]: r[value] for r in df.collect()}


def close(got, want):
    assert got.keys() == want.keys()
    for k in want:
        assert got[k] == pytest.approx(want[k], abs=1e-9)


@pytest.fixture(scope="module")
def toy(spark):
    return graphs.toy_graph(spark)


def test_worked_example_scores(toy):
    close(values(scores.walk_score(toy, 3)), {1: 0.8, 2: 0.37, 3: 0.9, 4: 0.0})
    close(values(scores.union_walk_score(toy, 3)), {1: 0.8, 2: 0.3628, 3: 0.9, 4: 0.0})
    close(values(scores.opinion_walk_score(toy, 3)), {1: 0.136, 2: 0.0465, 3: -0.351, 4: 0.0})
    close(values(scores.opinion_path_score(toy, 3, 1.0)), {1: 0.136, 2: 0.0465, 3: -0.351, 4: 0.0})


def test_worked_example_exact(toy):
    close(values(spread.exact_spread(toy), value="spread"), {1: 0.8, 2: 0.3628, 3: 0.9, 4: 0.0})
    close(values(spread.exact_spread(toy, opinion=True), value="spread"), {1: 0.136, 2: 0.047436, 3: -0.351, 4: 0.0})


def test_worked_example_seed(toy):
    assert seeds.score_greedy_seeds(toy, 1).first()["id"] == 3
    assert seeds.score_greedy_seeds(toy, 1, opinion=True).first()["id"] == 1


def test_all_negative_scores_give_no_seed(spark):
    g = graph(spark.createDataFrame([(1, 2)], "u long, v long"), spark.createDataFrame([(1, -1.0), (2, -1.0)], "id long, o double"))
    g = params.assign_ic(g)
    assert seeds.score_greedy_seeds(g, 1, opinion=True).count() == 0
    assert seeds.score_greedy_seeds(g, 1, opinion=True, allow_nonpositive=True).count() == 1


def test_spread_is_not_monotone(spark):
    rows = errors.submodularity(spark, graphs.two_layer_graph(spark, 4), [1, 4, 2])
    assert [round(r["spread"], 9) for r in rows.orderBy("size").collect()] == [1.0, 0.0, 1.0]


def test_live_edges_keep_one_arc_a_head(spark):
    edges = spark.createDataFrame([(u, 10 + v) for u in range(6) for v in range(3)], "u long, v long")
    live = diffusion.live_edges(params.assign_lt(graph(edges)), 20)
    assert live.groupBy("world", "v").count().agg(F.max("count")).first()[0] == 1
    assert live.count() == 20 * 3


def test_certain_arcs_reach_everything_and_none_reach_nothing(spark):
    edges = spark.createDataFrame([(1, 2), (2, 3), (3, 1), (3, 4)], "u long, v long")
    one = spark.createDataFrame([(1,)], "id long")
    sure = params.assign_ic(graph(edges), 1.0)
    assert {r["id"] for r in diffusion.cascade_ic(sure, one, 2).where("world = 0").collect()} == {1, 2, 3, 4}
    assert diffusion.cascade_ic(params.assign_ic(graph(edges), 0.0), one, 2).count() == 2


def test_bits_equal_rows(spark):
    edges = spark.createDataFrame([(u, (u * 7 + k) % 30) for u in range(30) for k in (1, 2, 3)], "u long, v long")
    g = params.assign_ic(graphs.normalize(graph(edges)), 0.3).materialized()
    one = spark.createDataFrame([(1,), (5,)], "id long")
    rows = {(r["id"], r["c"]) for r in diffusion.cascade_ic(g, one, 64).groupBy("id").agg(F.count(F.lit(1)).alias("c")).collect()}
    bits = {(r["id"], r["c"]) for r in diffusion.reach_bits(g, one, 1).select("id", F.bit_count("bits").alias("c")).where("c > 0").collect()}
    assert rows == bits


def test_no_opinion_and_full_agreement_is_the_classical_problem(spark):
    edges = spark.createDataFrame([(1, 2), (1, 3), (2, 4), (3, 4)], "u long, v long")
    g = graph(edges)
    g = graphs.InfluenceGraph(g.nodes.withColumn("o", F.lit(1.0)), g.edges.withColumn("phi", F.lit(1.0)).withColumn("p", F.lit(0.5)))
    act = diffusion.cascade_ic(g, spark.createDataFrame([(1,)], "id long"), 16)
    assert act.where("o_final <> 1").count() == 0


def test_lazy_equals_plain_greedy(spark):
    edges = spark.createDataFrame([(u, (u * 5 + k) % 20) for u in range(20) for k in (1, 2, 3)], "u long, v long")
    g = params.assign_ic(graphs.normalize(graph(edges)), 0.3).materialized()
    assert seeds.lazy_greedy_seeds(g, 3, 8).collect() == seeds.mc_greedy_seeds(g, 3, 8).collect()


def test_delta_rescoring_equals_full(spark):
    edges = spark.createDataFrame([(u, (u * 5 + k) % 20) for u in range(20) for k in (1, 2)], "u long, v long")
    g = params.assign_ic(graphs.normalize(graph(edges)), 0.3).materialized()
    removed = spark.createDataFrame([(3,), (7,)], "id long")
    close(values(scores.rescore_delta(g, scores.walk_score(g, 3), removed, 3)), values(scores.walk_score(g.without(removed), 3)))


def test_empty_graph(spark):
    g = graph(spark.createDataFrame([], "u long, v long"))
    assert scores.walk_score(g, 3).count() == 0
    assert seeds.score_greedy_seeds(g, 2).count() == 0


def test_normalize_mends_and_violations_find(spark):
    g = graph(spark.createDataFrame([(1, 1, 0.5), (1, 2, 0.5), (1, 2, 0.7), (2, 3, 1.5)], "u long, v long, p double"))
    bad = values(graphs.violations(g), "rule", "n")
    assert bad["self_loop"] == 1 and bad["repeated"] == 1 and bad["range"] == 1
    assert all(v == 0 for v in values(graphs.violations(graphs.normalize(g)), "rule", "n").values())


def test_max_cover(spark):
    sets = spark.createDataFrame([(1, 1), (2, 1), (2, 2), (3, 2), (4, 3)], "rr long, id long")
    assert [r["id"] for r in baselines.max_cover(sets, 2).orderBy("rank").collect()] == [1, 2]


@pytest.mark.parametrize("name", ["mc_greedy_k2", "opinion_mc_greedy_k2", "oc_greedy_k2", "lazy_greedy_k2"])
def test_registered_greedy_looks_beyond_high_degrees(spark, monkeypatch, name):
    dead = [(u, 100 + v, 0.0) for u in range(1, 13) for v in range(3)]
    rows = dead + [(500, 501, 1.0), (500, 502, 1.0), (600, 601, 1.0)]
    edges = spark.createDataFrame([(u, v, p, p, 1.0) for u, v, p in rows], "u long, v long, p double, w double, phi double")
    ids = sorted({x for u, v, _ in rows for x in (u, v)})
    g = graphs.InfluenceGraph(spark.createDataFrame([(i, 1.0, 0.5) for i in ids], "id long, o double, theta double"), edges).materialized()
    monkeypatch.setattr(workloads, "base_graph", lambda *_: g)
    assert [(r["id"], r["score"]) for r in workloads.REGISTRY[name](spark, "").orderBy("rank").collect()] == [(500, 2.0), (600, 3.0)]


def test_simple_path_greedy_goes_on_to_the_next_block(spark):
    rows = [(10 + c, 1, 0.5) for c in range(4)] + [(1, 100 + v, 1.0) for v in range(10)] + [(2, 200 + v, 1.0) for v in range(3)]
    edges = spark.createDataFrame([(u, v, w, w) for u, v, w in rows], "u long, v long, p double, w double")
    g = graph(edges).materialized()
    want = [(1, 11.0), (2, 15.0)]
    assert [(r["id"], r["score"]) for r in baselines.simpath_seeds(g, 2, max_len=4, block=2).orderBy("rank").collect()] == want
    assert [(r["id"], r["score"]) for r in baselines.simpath_seeds(g, 2, max_len=4).orderBy("rank").collect()] == want


def test_registered_cascades_run_to_the_end_of_a_chain(spark, monkeypatch):
    rows = [(0, k, 1.0) for k in (1, 21, 22)] + [(k, k + 1, 1.0) for k in range(1, 20)]
    edges = spark.createDataFrame([(u, v, p, p, 1.0) for u, v, p in rows], "u long, v long, p double, w double, phi double")
    g = graphs.InfluenceGraph(spark.createDataFrame([(i, 1.0, 0.5) for i in range(23)], "id long, o double, theta double"), edges).materialized()
    monkeypatch.setattr(workloads, "base_graph", lambda *_: g)
    monkeypatch.setattr(workloads, "top", lambda *_: spark.createDataFrame([(0,)], "id long"))
    for name in ("cascade_ic", "cascade_lt", "cascade_live_edge", "reach_bits"):
        assert {r["id"] for r in workloads.REGISTRY[name](spark, "").collect()} == set(range(23))
    assert workloads.REGISTRY["expected_spread"](spark, "").first()["spread"] == 22


def test_sketched_diameter_of_a_chain(spark):
    g = graph(spark.createDataFrame([(k, k + 1) for k in range(12)], "u long, v long"))
    # 91 pairs within 12 hops, of which 81.9 are the goal: 76 within 7 hops, 81 within 8, 85 within 9.
    got = graphs.profile_sketch(g).first()
    assert got["pairs"] == 91 and got["diameter90"] == pytest.approx(8 + 0.9 / 4)


def test_registered_reverse_sets_reach_the_start_of_a_chain(spark, monkeypatch):
    edges = spark.createDataFrame([(k, k + 1) for k in range(12)], "u long, v long")
    g = params.assign_ic(graph(edges), 1.0).materialized()
    monkeypatch.setattr(workloads, "base_graph", lambda *_: g)
    assert [(r["id"], r["score"]) for r in workloads.REGISTRY["rr_cover_k3"](spark, "").collect()] == [(0, 200.0)]
    assert [r["id"] for r in workloads.REGISTRY["rr_seeds"](spark, "").collect()] == [0]


def test_reverse_sampling_draws_what_the_bound_asks_for(spark):
    g = params.assign_ic(graph(spark.createDataFrame([(k, k + 1000) for k in range(400)], "u long, v long")), 0.1).materialized()
    report = baselines.rr_seeds(g, 1, eps=0.1)[1]
    assert report["drawn"] == report["wanted"] > 200_000 and not report["truncated"]


def test_length_report_searches_all_nodes(spark, monkeypatch):
    seen = []
    g = params.assign_ic(graph(spark.createDataFrame([(k, k + 20) for k in range(12)], "u long, v long")), 1.0).materialized()
    monkeypatch.setattr(reports, "_base", lambda *_: g)
    monkeypatch.setattr(reports, "_value", lambda *_: 0.0)
    monkeypatch.setattr(reports.seeds, "score_greedy_seeds", lambda *_, **__: spark.range(1))
    monkeypatch.setattr(reports.seeds, "mc_greedy_seeds", lambda *_, **kw: seen.append(kw.get("candidates")) or spark.range(1))
    reports.w09_length_opinion(spark, "")
    assert seen == [None]


def test_comparison_report_runs_the_real_baselines(spark, monkeypatch):
    seen = {}
    monkeypatch.setattr(reports, "_base", lambda *_: graph(spark.createDataFrame([(1, 2)], "u long, v long")))
    monkeypatch.setattr(reports, "_value", lambda *_: 1.0)
    for module, names in ((reports.seeds, ["score_greedy_seeds", "lazy_greedy_seeds", "degree_seeds", "random_seeds"]), (reports.baselines, ["rr_seeds", "influence_rank_seeds", "simpath_seeds"])):
        for name in names:
            monkeypatch.setattr(module, name, lambda *_, name=name, **kw: seen.update({name: kw}) or ((spark.range(1), {}) if name == "rr_seeds" else spark.range(1)))
    reports.w15_baselines(spark, "")
    assert "candidates" not in seen["lazy_greedy_seeds"] and {"rr_seeds", "influence_rank_seeds", "simpath_seeds"} <= set(seen)


def test_one_cascade_gives_the_spreads_of_all_topic_models(spark, monkeypatch):
    from rippletide.operators import topics

    members = spark.createDataFrame([(t, 0, u, float(u)) for t in (1, 2) for u in range(12)], "topic int, epoch long, user_id long, opinion double")
    edges = spark.createDataFrame([(t, 0, u, (u * 5 + k) % 12) for t in (1, 2) for u in range(12) for k in (1, 2)], "topic int, epoch long, u long, v long")
    origin = spark.createDataFrame([(1, 0, 0), (2, 0, 3)], "topic int, epoch long, user_id long")
    opinions = spark.createDataFrame([(t, u, (-1) ** u * u / 12) for t in (1, 2) for u in range(12)], "topic int, user_id long, estimate double")
    phi = spark.createDataFrame([(u, v, 0.3) for u in range(12) for v in range(12)], "u long, v long, phi double")
    runs, run, graphs_seen = [], diffusion.cascade_ic, []
    monkeypatch.setattr(diffusion, "cascade_ic", lambda g, *a, **kw: runs.append(1) or graphs_seen.append(g) or run(g, *a, **kw))
    got = {(r["topic"], r["model"]): r["spread"] for r in topics.model_spreads(members, edges, origin, opinions, phi, 8).collect()}
    assert len(runs) == 1
    where = members.select("topic", F.xxhash64("topic", "epoch", "user_id").alias("id"))
    starts = origin.select(F.xxhash64("topic", "epoch", "user_id").alias("id"))
    want = {}
    for name, model, value in (("oi", "ic", F.col("o_final")), ("oc", "oc-ic", F.col("o_final")), ("ic", "ic", F.lit(1.0))):
        act = spread.simulate(graphs_seen[0], starts, 8, model=model)
        want |= {(r["topic"], name): r["s"] for r in act.where("step > 0").join(where, "id").groupBy("topic").agg((F.sum(value) / 8).alias("s")).collect()}
    close(got, want)
