"""Synthetic graphs as a Spark data source: grid, ring, star and random edges, made in parallel."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class GraphSource(DataSource):
    """Options: kind (grid, ring, star, random), n (vertices; a grid has n columns and rows), degree (random), slices."""

    @classmethod
    def name(cls) -> str:
        return "manyq_graph"

    def schema(self) -> str:
        return "x long, y long"

    def reader(self, schema) -> DataSourceReader:
        return GraphReader(self.options)


class GraphReader(DataSourceReader):
    def __init__(self, options):
        self.kind, self.n = options.get("kind", "grid"), int(options.get("n", "10"))
        self.degree, self.slices = int(options.get("degree", "4")), int(options.get("slices", "4"))

    def partitions(self) -> list[InputPartition]:
        return [InputPartition((i * self.n // self.slices, (i + 1) * self.n // self.slices)) for i in range(self.slices)]

    def read(self, partition: InputPartition) -> Iterator[tuple[int, int]]:
        n = self.n
        for i in range(*partition.value):
            if self.kind == "ring":
                yield i, (i + 1) % n
            elif self.kind == "star":
                if i:
                    yield 0, i
            elif self.kind == "grid":
                for j in range(n):
                    if j + 1 < n:
                        yield i * n + j, i * n + j + 1
                    if i + 1 < n:
                        yield i * n + j, (i + 1) * n + j
            elif self.kind == "random":
                for k in range(self.degree):
                    yield i, (i * 7919 + k * 104729 + 1) * 48271 % 2147483647 % n
            else:
                raise ValueError(self.kind)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(GraphSource)
