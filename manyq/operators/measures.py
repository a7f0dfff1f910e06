"""Cost and accuracy measures over traces, plans and results."""

from __future__ import annotations

from collections import OrderedDict

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def cache_model(visits: list[int], capacity: int) -> tuple[int, int]:
    """(loads, misses) of a sequence of block visits with room for so many blocks, least recently used first out.

    It stands in for a processor's cache counters, which Spark does not have.
    """
    held: OrderedDict[int, None] = OrderedDict()
    misses = 0
    for block in visits:
        if block in held:
            held.move_to_end(block)
            continue
        misses += 1
        held[block] = None
        if len(held) > capacity:
            held.popitem(last=False)
    return len(visits), misses


def visit_counts(trace: DataFrame) -> DataFrame:
    """(part_id, visits, revisits, edges)."""
    return trace.groupBy("part_id").agg(F.count("*").alias("visits"), (F.count("*") - 1).alias("revisits"), F.sum("edges").alias("edges"))


def work_ratio(edges: float, sequential: float) -> float:
    return edges / sequential


def cpu_inflation(cores: int, parallel: float, single: float) -> float:
    """CPU time of a run on so many cores over that of the single-threaded run."""
    return cores * parallel / single


def speedup(baseline: float, own: float) -> float:
    return baseline / own


def state_bytes(state: DataFrame, row_bytes: int = 44) -> int:
    """Memory of results and state, by rows and width."""
    return state.count() * row_bytes


def differing_rows(a: DataFrame, b: DataFrame) -> int:
    """Rows in one and not in the other: none where two runs are exact."""
    b = b.select(*a.columns)
    return a.exceptAll(b).count() + b.exceptAll(a).count()


def ppr_error(estimate: DataFrame, exact: DataFrame, degrees: DataFrame, eps: float) -> DataFrame:
    """(query_id, max_error, l1, bound_ok): exact minus estimate, and whether it lies between 0 and eps times the degree."""
    both = exact.withColumnRenamed("p", "exact").join(estimate.select("query_id", "v", "p"), ["query_id", "v"], "left").join(degrees.select(F.col("id").alias("v"), "deg"), "v")
    gap = F.col("exact") - F.coalesce("p", F.lit(0.0))
    return both.groupBy("query_id").agg(F.max(gap).alias("max_error"), F.sum(F.abs(gap)).alias("l1"), F.bool_and((gap >= -1e-9) & (gap <= eps * F.col("deg") + 1e-9)).alias("bound_ok"))


def score_error(sampled: DataFrame, exact: DataFrame) -> DataFrame:
    """(max_relative, correlation) of sampled scores (v, score) against exact ones."""
    both = exact.withColumnRenamed("score", "exact").join(sampled, "v")
    return both.agg(F.max(F.when(F.col("exact") > 0, F.abs(F.col("score") - F.col("exact")) / F.col("exact"))).alias("max_relative"), F.corr("score", "exact").alias("correlation"))
