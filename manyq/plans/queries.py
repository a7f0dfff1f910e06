"""The query kinds on the buffered engine, as tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from manyq.operators.blocks import BlockedGraph
from manyq.plans.baselines import frontier_run
from manyq.plans.engine import ForkResult, fork
from manyq.plans.kernels import KShortest, Push, Relax, Token, Walk
from manyq.plans.policy import Policy


def _long(name: str, alias: str):
    return F.col(name).cast("long").alias(alias)


def levels_of(r: ForkResult) -> DataFrame:
    return r.state.select("query_id", "v", _long("num", "level"), _long("aux", "parent"))


def lengths_of(r: ForkResult) -> DataFrame:
    return r.state.select("query_id", "v", _long("num", "dist"), _long("aux", "pred"))


def _alone(bg: BlockedGraph, sources: DataFrame, weighted: bool, policy: Policy | None) -> DataFrame | None:
    """One operation and nothing else to run: where the policy asks for it, the whole cluster follows its frontier."""
    if policy is None or not policy.alone or sources.limit(2).count() != 1:
        return None
    return frontier_run(bg.graph, sources, weighted).state


def multi_bfs(bg: BlockedGraph, sources: DataFrame, max_depth: int | None = None, policy: Policy | None = None) -> DataFrame:
    """(query_id, v, level, parent)."""
    if max_depth is None and (found := _alone(bg, sources, False, policy)) is not None:
        return found.withColumnsRenamed({"dist": "level", "pred": "parent"})
    return levels_of(fork(bg, sources, Relax(False, max_depth), policy or Policy.levels(), traced=False))


def multi_sssp(bg: BlockedGraph, sources: DataFrame, cutoff: float | None = None, policy: Policy | None = None) -> DataFrame:
    """(query_id, v, dist, pred)."""
    if cutoff is None and (found := _alone(bg, sources, True, policy)) is not None:
        return found
    return lengths_of(fork(bg, sources, Relax(True, cutoff), policy or Policy.paths(), traced=False))


def multi_ppr(bg: BlockedGraph, sources: DataFrame, alpha: float = 0.15, eps: float = 1e-5, lazy: bool = False, policy: Policy | None = None) -> DataFrame:
    """(query_id, v, p, r)."""
    r = fork(bg, sources, Push(alpha, eps, lazy), policy or Policy.ppr(None), traced=False)
    return r.state.select("query_id", "v", F.col("num").alias("p"), F.col("rest").alias("r"))


def multi_dfs(bg: BlockedGraph, sources: DataFrame, policy: Policy | None = None) -> DataFrame:
    """(query_id, v, pre, parent, depth)."""
    r = fork(bg, sources, Token(), policy or Policy.fifo())
    return r.state.select("query_id", "v", _long("num", "pre"), _long("aux", "parent"), _long("aux2", "depth"))


def multi_walk(bg: BlockedGraph, sources: DataFrame, length: int, walks: int, restart: float = 0.0, bias: str = "uniform", seed: int = 0, policy: Policy | None = None) -> DataFrame:
    """(query_id, walk, step, v)."""
    r = fork(bg, sources, Walk(length, walks, restart, bias, seed), policy or Policy.fifo())
    return r.state.select("query_id", _long("aux", "walk"), _long("aux2", "step"), "v")


def multi_kshortest(bg: BlockedGraph, sources: DataFrame, k: int, weighted: bool = True, policy: Policy | None = None) -> DataFrame:
    """(query_id, v, rank, dist): the lengths of the k shortest walks, ranks from 0."""
    r = fork(bg, sources, KShortest(k, weighted), policy or Policy.paths())
    return r.state.select("query_id", "v", _long("aux2", "rank"), _long("num", "dist"))


def closeness(lengths: DataFrame) -> DataFrame:
    """(query_id, reached, total, closeness) from (query_id, v, dist)."""
    return lengths.groupBy("query_id").agg(F.count("*").alias("reached"), F.sum("dist").cast("long").alias("total")).select(
        "query_id", "reached", "total", F.round(F.when(F.col("total") > 0, (F.col("reached") - 1) / F.col("total")).otherwise(0.0), 6).alias("closeness")
    )
