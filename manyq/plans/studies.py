"""The published comparisons as runs of arms: each arm answers the same queries, and is timed and counted.

A row of a study: (arm, rows, total, waves, visits, edges, sent, loads, misses, seconds). rows and total are the answer's
digest (reached vertices, sum of values), which must be alike in all arms; the rest is cost.
"""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from manyq.operators import measures, partition
from manyq.operators.blocks import BlockedGraph, blocked
from manyq.plans import baselines
from manyq.plans.engine import ForkResult, fork
from manyq.plans.kernels import Kernel, Push, Relax
from manyq.plans.policy import Policy, YieldPolicy, policy_ladder
from manyq.sources.graphs import Graph

ROW = "arm string, rows long, total double, waves int, visits int, edges long, sent long, loads long, misses long, seconds double"
Arm = Callable[[], ForkResult | DataFrame]


def study(spark: SparkSession, arms: dict[str, Arm], value: str = "num", cache: int = 4) -> DataFrame:
    """Run arms in turn: a list of a few rows, made on the driver."""
    out = []
    for name, run in arms.items():
        began = time.time()
        r = run()
        state, result = (r.state, r) if isinstance(r, ForkResult) else (r, None)
        column = value if value in state.columns else "dist" if "dist" in state.columns else "p"
        rows, total = state.agg(F.count("*"), F.round(F.sum(column), 4).cast("double")).first()
        took = round(time.time() - began, 2)
        trace = result.trace if result else []
        loads, misses = measures.cache_model([t[1] for t in trace], cache)
        edges, sent = (result.total("edges"), result.total("ops_sent")) if result else (0, 0)
        out.append((name, rows, total, result.waves if result else 0, len(trace), edges, sent, loads, misses, took))
    return spark.createDataFrame(out, ROW)


def ladder(bg: BlockedGraph, sources: DataFrame, kernel: Kernel, pause: YieldPolicy, wave_width: int | None = 1) -> dict[str, Arm]:
    """Buffering, consolidation, priority and yielding, added one by one; a kernel that sums cannot be split, so its ladder begins with consolidation."""
    arms = policy_ladder(pause, wave_width)
    if kernel.combine != "min":
        arms.pop("buffer")
    return {name: lambda p=p: fork(bg, sources, kernel, p) for name, p in arms.items()}


def schedulers(bg: BlockedGraph, sources: DataFrame, kernel: Kernel, pause: YieldPolicy, wave_width: int = 1) -> dict[str, Arm]:
    return {name: lambda n=name: fork(bg, sources, kernel, Policy(scheduler=n, pause=pause, wave_width=wave_width)) for name in ("random", "max_ops", "fifo", "priority")}


def yields(bg: BlockedGraph, sources: DataFrame, kernel: Kernel, delta: float, wave_width: int = 1, factors=(0.25, 0.5, 1, 2, 4)) -> dict[str, Arm]:
    """Edge budgets in units of mu, value ranges in units of delta, and no yielding."""
    pauses = {f"edges_{f}": YieldPolicy(edges=f) for f in factors} | {f"range_{f}": YieldPolicy(delta=f * delta) for f in factors} | {"none": YieldPolicy.none()}
    return {name: lambda p=p: fork(bg, sources, kernel, Policy(pause=p, wave_width=wave_width)) for name, p in pauses.items()}


def partitioners(g: Graph, sources: DataFrame, kernel: Kernel, parts: int, policy: Policy | None = None) -> dict[str, Arm]:
    plans = {"random": partition.partition_random, "chunk_edges": lambda g, p: partition.partition_chunk(g, p, "edges"), "multilevel": partition.partition_multilevel}
    return {name: lambda plan=plan: fork(blocked(g, plan(g, parts)), sources, kernel, policy) for name, plan in plans.items()}


def block_sizes(g: Graph, sources: DataFrame, kernel: Kernel, block_bytes: float, factors=(0.25, 0.5, 1, 2, 4), policy: Policy | None = None) -> dict[str, Arm]:
    """Blocks of a quarter to four times a size."""
    total = partition.graph_stats(g).first()["bytes"]
    counts = {f: partition.partition_count(total, f * block_bytes) for f in factors}
    return {f"blocks_{f}": lambda n=n: fork(blocked(g, parts=n), sources, kernel, policy) for f, n in counts.items()}


def systems(g: Graph, bg: BlockedGraph, sources: DataFrame, weighted: bool, slots: int, ts=("single", "all", 1)) -> dict[str, Arm]:
    """The three systems that the engine is compared with, by threads a query: all slots on one query, one slot each, one slot in all; and the engine."""
    runs = {"frontier": {}, "message_passing": {"materialise_messages": True}, "segmented": {"segments": 4}}
    arms: dict[str, Arm] = {"buffered": lambda: fork(bg, sources, Relax(weighted))}
    for name, how in runs.items():
        for t in ts:
            pool = {"single": 1, "all": 1}.get(t) or max(1, slots // t)
            arms[f"{name}_{t}"] = lambda how=how, pool=pool, t=t: baselines.pooled(g, sources, weighted, pool, 1 if t == "single" else None, **how)
    return arms


def ppr_systems(g: Graph, bg: BlockedGraph, sources: DataFrame, rounds: int = 20) -> dict[str, Arm]:
    """Personalised ranks of many sources by the three systems' power iterations, and pushed by the engine."""
    how = {"frontier": {}, "message_passing": {"materialise_messages": True}, "segmented": {"segments": 4}}
    arms: dict[str, Arm] = {name: lambda h=h: baselines.ppr_power(g, sources, rounds=rounds, **h) for name, h in how.items()}
    return arms | {"buffered": lambda: fork(bg, sources, Push(0.15, 1e-5), Policy.ppr(None))}


def query_scaling(bg: BlockedGraph, make_sources: Callable[[int], DataFrame], kernel: Kernel, sizes=(16, 32, 64)) -> dict[str, Arm]:
    return {f"queries_{n}": lambda n=n: fork(bg, make_sources(n), kernel) for n in sizes}
