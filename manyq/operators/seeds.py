"""Choice of source vertices and batches of queries."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from manyq.functions.ids import draw_order
from manyq.operators.partition import global_rank
from manyq.sources.graphs import Graph


def _numbered(chosen: DataFrame, *order) -> DataFrame:
    """(query_id, src) in the order drawn; what is numbered is a batch of queries, small by design."""
    return chosen.select((F.row_number().over(Window.orderBy(*order)) - 1).cast("int").alias("query_id"), F.col("id").alias("src"))


def sample_sources(g: Graph, n: int, seed: int = 1) -> DataFrame:
    order = (draw_order(F.col("id"), seed), F.col("id"))
    return _numbered(g.vertices.orderBy(*order).limit(n), *order)


def sample_fraction(g: Graph, fraction: float, seed: int = 1, least: int = 16) -> DataFrame:
    return sample_sources(g, max(least, math.ceil(fraction * g.n_vertices)), seed)


def all_sources(g: Graph) -> DataFrame:
    """Every vertex, numbered by id without one task that sees all."""
    return global_rank(g.vertices, F.col("id"), F.col("id")).select(F.col("rank").cast("int").alias("query_id"), F.col("id").alias("src"))


def top_degree(g: Graph, n: int) -> DataFrame:
    order = (F.desc("deg"), F.col("id"))
    return _numbered(g.vertices.orderBy(*order).limit(n), *order)


def landmarks(g: Graph, n: int, how: str = "random", seed: int = 1) -> DataFrame:
    if how not in ("random", "degree"):
        raise ValueError(how)
    return sample_sources(g, n, seed) if how == "random" else top_degree(g, n)


def batches(sources: DataFrame, size: int) -> DataFrame:
    """sources with the batch each query belongs to."""
    return sources.withColumn("batch", F.floor(F.col("query_id") / size).cast("int"))


SOURCES_SQL = "src AS MATERIALIZED (SELECT (row_number() OVER (ORDER BY (id * 7919 + {seed}) % 10007, id) - 1)::INTEGER AS query_id, id AS src FROM v QUALIFY query_id < {n})"


def sources_sql(n: int, seed: int = 1) -> str:
    return SOURCES_SQL.format(n=n, seed=seed)
