"""Headline queries at ``$BENCH_SF_DIR`` on ``local[$BENCH_CPUS]``; prints one JSON line."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession

from rippletide.operators import baselines, diffusion, graphs, params, scores, seeds
from rippletide.operators.graphs import graph
from rippletide.plans.storage import stored


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", "8g")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    took: dict[str, float] = {}

    def timed(name, run):
        began = time.perf_counter()
        out = run()
        took[name] = round(time.perf_counter() - began, 2)
        return out

    def done(df):
        df.write.format("noop").mode("overwrite").save()

    g = timed("build_copurchase_w2", lambda: params.interactions_uniform(params.opinions_uniform(graph(stored(graphs.copurchase_edges(spark, sf).select("u", "v"))))).materialized())
    big = timed("build_copurchase_w1", lambda: graph(stored(graphs.copurchase_edges(spark, sf, 1).select("u", "v"))).materialized())
    timed("walk_score_l3_w1", lambda: done(scores.walk_score(big, 3)))
    timed("opinion_walk_score_l3_w1", lambda: done(scores.opinion_walk_score(big, 3)))
    timed("union_walk_score_l2", lambda: done(scores.union_walk_score(g, 2)))
    timed("score_greedy_k5", lambda: done(seeds.score_greedy_seeds(g, 5, 3, discount="seed")))
    timed("opinion_score_greedy_k5", lambda: done(seeds.score_greedy_seeds(g, 5, 3, True, "seed")))
    timed("influence_rank_seeds_k5", lambda: done(baselines.influence_rank_seeds(g, 5)))
    timed("cascade_ic_1000_worlds", lambda: done(diffusion.cascade_ic(g, seeds.degree_seeds(g, 10).select("id"), 1000)))
    timed("reach_bits_10240_worlds", lambda: done(diffusion.reach_bits(g, seeds.degree_seeds(g, 10).select("id"), 160)))
    print(json.dumps({"metric": "total_seconds", "value": round(sum(took.values()), 2), "unit": "sec", "queries": took, "sf": os.path.basename(sf.rstrip("/"))}))


if __name__ == "__main__":
    main()
