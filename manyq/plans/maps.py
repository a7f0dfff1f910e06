"""The interface of frontier programs: vertex_map and edge_map, on tables of (query_id, v, ...)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def vertex_map(vertices: DataFrame, keep: Column | None = None, **changes: Column) -> DataFrame:
    """vertices with columns changed or added, and of them those that `keep`, on the changed columns, holds for."""
    out = vertices.withColumns(changes) if changes else vertices
    return out if keep is None else out.where(keep)


def edge_map(frontier: DataFrame, edges: DataFrame, update: Column, reached: Column | None = None, combine=F.min) -> DataFrame:
    """(query_id, v, value): what the out-edges of a frontier (query_id, v, ...) give to their targets, combined by target.

    update: from the frontier's columns and `src`, `dst`, `w`; reached: which edges count. Combining before the exchange and
    after it is Spark's partial aggregation.
    """
    met = frontier.withColumnRenamed("v", "src").join(edges, "src")
    met = met if reached is None else met.where(reached)
    return met.groupBy("query_id", F.col("dst").alias("v")).agg(combine(update).alias("value"))
