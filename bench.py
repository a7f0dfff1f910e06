"""Headline timings: one JSON line. BENCH_SF_DIR and BENCH_CPUS choose tables and threads.

`ratios` holds what the published figures are compared by: work and time of the engine's arms against each other.
"""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession


def main() -> None:
    cpus, sf_dir = os.environ.get("BENCH_CPUS", "8"), os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("manyq-bench").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from manyq.operators import measures, partition, seeds
    from manyq.operators.blocks import blocked
    from manyq.plans import apps, baselines
    from manyq.plans.engine import fork
    from manyq.plans.kernels import Push, Relax
    from manyq.plans.policy import Policy, YieldPolicy
    from manyq.sources import graphs

    took: dict[str, float] = {}
    ratios: dict[str, float] = {}

    def timed(name: str, run):
        began = time.time()
        out = run()
        if hasattr(out, "write"):
            out.write.format("noop").mode("overwrite").save()
        took[name] = round(time.time() - began, 2)
        print(name, took[name], file=sys.stderr, flush=True)
        return out

    road, social = graphs.event_grid(spark, sf_dir), graphs.trade(spark, sf_dir)
    road_blocks = timed("pack_road", lambda: blocked(road, parts=8))
    social_blocks = timed("pack_social", lambda: blocked(social, partition.partition_random(social, 8)))
    marks, people = seeds.sample_sources(road, 64), seeds.sample_fraction(social, 0.0001)

    # Landmark labels on the road-like graph: the engine, against queries at a time in whole-graph workers.
    own = timed("ll_road_buffered", lambda: fork(road_blocks, marks, Relax(True), Policy.paths()))
    timed("ll_road_interquery", lambda: baselines.inter_query_run(road, marks, True, slots=int(cpus)))
    arrival = timed("ll_road_arrival_order", lambda: fork(road_blocks, marks, Relax(True), Policy(order="fifo")))
    sequential = baselines.inter_query_run(road, marks, True, slots=int(cpus)).select("query_id", "edges").distinct().groupBy().sum("edges").first()[0]
    ratios["ll_road_edges_to_sequential"] = round(measures.work_ratio(own.total("edges"), sequential), 3)
    ratios["ll_road_arrival_edges_to_heap_edges"] = round(arrival.total("edges") / own.total("edges"), 3)
    ratios["ll_road_waves"] = own.waves
    loads, misses = measures.cache_model([t[1] for t in own.trace], 4)
    # Each query alone passes over all blocks it touches: that many loads, all missed once blocks outnumber the cache.
    ratios["ll_road_block_loads_shared_to_alone"] = round(loads / max(1, sum(t[2] for t in own.trace)), 4)
    ratios["ll_road_block_misses_to_loads"] = round(misses / loads, 3)

    # Queries of few levels on the social-like graph: frontier systems at their best.
    few = seeds.sample_sources(social, 8)
    timed("bfs_social_buffered", lambda: fork(social_blocks, few, Relax(False), Policy.levels()))
    timed("bfs_social_shared_frontier", lambda: baselines.shared_frontier_run(social, few, False))
    timed("bfs_social_bsp", lambda: baselines.bsp_run(social, few, False))
    timed("bfs_social_segmented", lambda: baselines.segmented_run(social, few, False))
    one = timed("bfs_social_frontier_one_by_one", lambda: baselines.frontier_run(social, few, False))
    ratios["bfs_social_frontier_time_to_buffered"] = round(took["bfs_social_frontier_one_by_one"] / took["bfs_social_buffered"], 2)
    ratios["bfs_social_bsp_time_to_buffered"] = round(took["bfs_social_bsp"] / took["bfs_social_buffered"], 2)
    assert one.waves

    # Community profile: pushes, pausing by residual, and the sweep.
    plain = timed("ppr_social_buffered", lambda: fork(social_blocks, people, Push(0.15, 1e-5), Policy.ppr(None)))
    paused = timed("ppr_social_paused", lambda: fork(social_blocks, people, Push(0.15, 1e-5), Policy(pause=YieldPolicy(factor=2))))
    ratios["ppr_social_paused_edges_to_plain"] = round(paused.total("edges") / plain.total("edges"), 3)
    ranks = plain.state.selectExpr("query_id", "v", "num AS p").where("p > 0")
    timed("ncp_sweep", lambda: apps.community_profile(apps.sweep(social, ranks)))
    timed("bc_web_bfs", lambda: apps.betweenness(blocked(graphs.hyperlink(spark, sf_dir), parts=4), seeds.sample_sources(graphs.hyperlink(spark, sf_dir), 100)))
    print(json.dumps({"metric": "total seconds of headline queries", "value": round(sum(took.values()), 2), "unit": "sec", "queries": took, "ratios": ratios, "sf": sf_dir.rstrip("/").rsplit("sf", 1)[-1]}))


if __name__ == "__main__":
    main()
