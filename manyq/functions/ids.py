"""Vertex ids of several tables in one space of longs, reproducible weights, and an integer generator that SQL can repeat."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

#: kind * SPACE + key.
SPACE = 10**12
PART, SUPPLIER, CUSTOMER, NATION, REGION, ORDER, EVENT, PAGE, DOCUMENT, ITEM, VECTOR, TOKEN = range(1, 13)


def vertex(kind: int, key: Column) -> Column:
    return key.cast("long") + F.lit(kind * SPACE)


def weight_range(n_vertices: int) -> int:
    """Weights are integers from 1 to below the logarithm of the vertex count (2 at least)."""
    return max(1, math.ceil(math.log2(max(2, n_vertices))) - 1)


def weight(src: Column, dst: Column, n_vertices: int) -> Column:
    """A weight that looks random, is alike both ways, and is the same in any SQL."""
    a, b = F.pmod(src, F.lit(SPACE)), F.pmod(dst, F.lit(SPACE))
    return (F.lit(1) + (F.least(a, b) * 7919 + F.greatest(a, b) * 104729) % weight_range(n_vertices)).cast("long")


def draw_order(id: Column, seed: int) -> Column:
    """The order in which source vertices are drawn."""
    return F.pmod(id * 7919 + seed, F.lit(10007))


def step_choice(query: int, walk: int, step: int, degree: int, seed: int = 0) -> int:
    """The neighbour that a walk takes at a step: the same numbers in Python and SQL."""
    return ((query * 7919 + walk * 104729 + step * 1299709 + seed) * 48271 % 2147483647) % degree


def step_choice_sql(query: str, walk: str, step: str, degree: str, seed: int = 0) -> str:
    return f"((({query})::BIGINT * 7919 + ({walk})::BIGINT * 104729 + ({step})::BIGINT * 1299709 + {seed}) * 48271 % 2147483647) % ({degree})"
