"""Connected components of a table of links, by alternating star contractions.

Every step is a grouped minimum joined back, so no neighbour list is ever gathered; a hub's links are rows that Spark
splits. Each round is written to the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from manyq.llm.common import materialise


def _least(links: DataFrame) -> DataFrame:
    """(u, v, m) for both directions of every link: m is the least of u and its neighbours."""
    both = links.select("u", "v").unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return both.join(least, "u")


def _state(links: DataFrame) -> tuple:
    return tuple(links.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v"))).first())


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(node, component): the least node that links, in either direction, lead to, for each node other than it.

    links: u, v of one orderable type. A node that is its component's least has no row. Raises if it does not end.
    """
    links = materialise(links.select("u", "v").where("u <> v").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct(), "links")
    before = _state(links)
    for _ in range(most_rounds):
        if not before[0]:
            return links.select(F.col("v").alias("node"), F.col("u").alias("component"))
        large = _least(links).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        near = _least(large)
        small = near.where("v <= u").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(near.select("u", F.col("m").alias("v")))
        links = materialise(small.where("u <> v").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct(), "links")
        after = _state(links)
        if after == before:
            return links.select(F.col("v").alias("node"), F.col("u").alias("component"))
        before = after
    raise RuntimeError(f"components did not settle in {most_rounds} rounds")
