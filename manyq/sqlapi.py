"""Table functions for SQL: whole queries inside one block, over a TABLE argument of edges partitioned by block.

A table function cannot start jobs, so queries across blocks are for the DataFrame interface.
"""

from __future__ import annotations

import heapq

from pyspark.sql import Row, SparkSession
from pyspark.sql.functions import udtf


class _Edges:
    """Collects a partition's rows (src, dst, w); terminate() runs from the least source asked for."""

    def __init__(self):
        self.out: dict[int, list[tuple[int, int]]] = {}
        self.source: int | None = None

    def eval(self, row: Row, source: int):
        self.source = source
        self.out.setdefault(row["src"], []).append((row["dst"], row["w"]))

    def _lengths(self, weighted: bool):
        if self.source is None or self.source not in self.out:
            return
        best, queue = {}, [(0, self.source)]
        while queue:
            d, v = heapq.heappop(queue)
            if v in best:
                continue
            best[v] = d
            for u, w in self.out.get(v, ()):
                if u not in best:
                    heapq.heappush(queue, (d + (w if weighted else 1), u))
        yield from best.items()


@udtf(returnType="v: long, dist: long")
class GraphSssp(_Edges):
    def terminate(self):
        yield from self._lengths(True)


@udtf(returnType="v: long, level: long")
class GraphBfs(_Edges):
    def terminate(self):
        yield from self._lengths(False)


@udtf(returnType="v: long, p: double")
class GraphPpr(_Edges):
    """Ranks by pushing, alpha 0.15, until no residual reaches 1e-7 times its vertex's degree."""

    def terminate(self):
        if self.source is None:
            return
        rank, rest, todo = {}, {self.source: 1.0}, [self.source]
        while todo:
            v = todo.pop()
            out, r = self.out.get(v, ()), rest.get(v, 0.0)
            if r < 1e-7 * max(1, len(out)):
                continue
            rank[v] = rank.get(v, 0.0) + (0.15 * r if out else r)
            rest[v] = 0.0
            for u, _ in out:
                rest[u] = rest.get(u, 0.0) + 0.85 * r / len(out)
                todo.append(u)
        yield from sorted(rank.items())


def register(spark: SparkSession) -> None:
    """graph_bfs, graph_sssp and graph_ppr, each of (TABLE(edges), source)."""
    spark.udtf.register("graph_bfs", GraphBfs)
    spark.udtf.register("graph_sssp", GraphSssp)
    spark.udtf.register("graph_ppr", GraphPpr)
