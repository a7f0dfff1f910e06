"""Blocks: a part's vertices with their out-edges in compressed rows, one or more chunks per part."""

from __future__ import annotations

import uuid
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from manyq.operators.partition import cut_large, partition_chunk
from manyq.sources.graphs import Graph, settled
from manyq.sources.tables import epoch


@dataclass
class BlockedGraph:
    graph: Graph
    vparts: DataFrame  # id, part_id
    packed: DataFrame | None  # part_id, chunk, vids, offsets, dst, dst_part, w; packed when first asked for if not given
    n_parts: int
    #: Names these blocks to the workers that keep them decoded; never given twice, unlike an id().
    token: str = field(default_factory=lambda: uuid.uuid4().hex)

    @cached_property
    def blocks(self) -> DataFrame:
        return self.packed if self.packed is not None else epoch(pack_blocks(self.graph, self.vparts), "blocks")

    @cached_property
    def fitted(self) -> tuple[DataFrame, DataFrame]:
        """(vparts, blocks) that the engine runs on: the plan's, or, where a part outgrows a task, with that part cut along the vertex order."""
        cut = cut_large(self.graph, self.vparts)
        if cut is None:
            return self.vparts, self.blocks
        vparts = epoch(cut, "vparts")
        return vparts, epoch(pack_blocks(self.graph, vparts), "blocks")


def pack_blocks(g: Graph, vparts: DataFrame, chunk_edges: int = 500_000, most_sent: int = 2_000_000) -> DataFrame:
    """Source-owned edges as arrays. A part with more edges than chunk_edges gets several chunks, so no row outgrows a task; vertices without out-edges are listed too.

    The plan is sent to all executors while it has at most most_sent vertices, so that edges are exchanged once, to their chunks.
    """
    sent = lambda df: F.broadcast(df) if g.n_vertices <= most_sent else df
    placed = g.edges.join(sent(vparts.select(F.col("id").alias("src"), "part_id")), "src").join(sent(vparts.select(F.col("id").alias("dst"), F.col("part_id").alias("dst_part"))), "dst")
    rows = placed.select("part_id", "src", "dst", "dst_part", "w").unionByName(vparts.select("part_id", F.col("id").alias("src")), allowMissingColumns=True)
    sizes = vparts.join(g.vertices.select("id", "deg"), "id", "left")
    chunks = F.broadcast(sizes.groupBy("part_id").agg(F.ceil((F.count("*") + F.coalesce(F.sum("deg"), F.lit(0))) / chunk_edges).cast("int").alias("chunks")))  # a row per part
    dealt = rows.join(chunks, "part_id").withColumn("chunk", F.pmod(F.xxhash64("src"), "chunks").cast("int")).drop("chunks")
    schema = "part_id int, chunk int, vids array<long>, offsets array<int>, dst array<long>, dst_part array<int>, w array<long>"
    return dealt.groupBy("part_id", "chunk").applyInArrow(_pack, schema)


def _pack(rows: pa.Table) -> pa.Table:
    """One chunk: vertices in order, each with its out-edges in order."""
    rows = rows.sort_by([("src", "ascending"), ("dst", "ascending")])
    src = rows["src"].to_numpy()
    real = rows["dst"].is_valid().to_numpy()
    vids, first = np.unique(src, return_index=True)
    before = np.concatenate([[0], np.cumsum(real)])
    offsets = np.append(before[first], before[-1]).astype(np.int32)
    own = rows.filter(rows["dst"].is_valid())
    one = lambda x, kind: pa.array([x], pa.list_(kind))
    return pa.table({"part_id": rows["part_id"][:1], "chunk": rows["chunk"][:1], "vids": one(vids, pa.int64()), "offsets": one(offsets, pa.int32()), "dst": one(own["dst"].to_numpy(), pa.int64()), "dst_part": one(own["dst_part"].to_numpy(), pa.int32()), "w": one(own["w"].to_numpy(), pa.int64())})


def blocked(g: Graph, vparts: DataFrame | None = None, parts: int = 8) -> BlockedGraph:
    """Partition (chunks of the vertex order unless given) and pack, both written once; packing waits until blocks are asked for."""
    settled(g)
    vparts = epoch(vparts if vparts is not None else partition_chunk(g, parts), "vparts")
    return BlockedGraph(g, vparts, None, vparts.agg(F.max("part_id")).first()[0] + 1 if g.n_vertices else 0)


def unpack_blocks(blocks: DataFrame) -> DataFrame:
    """(part_id, src, dst, dst_part, w) again."""
    size = F.transform(F.sequence(F.lit(1), F.size("vids")), lambda i: F.element_at("offsets", i + 1) - F.element_at("offsets", i))
    owner = F.flatten(F.zip_with("vids", size, lambda v, n: F.array_repeat(v, n)))
    zipped = F.arrays_zip(owner.alias("src"), F.col("dst").alias("dst"), F.col("dst_part").alias("dst_part"), F.col("w").alias("w"))
    return blocks.select("part_id", F.explode(zipped).alias("x")).select("part_id", "x.src", "x.dst", "x.dst_part", "x.w")


def block_stats(blocks: DataFrame) -> DataFrame:
    """(part_id, vertices, edges, bytes)."""
    return blocks.groupBy("part_id").agg(F.sum(F.size("vids")).alias("vertices"), F.sum(F.size("dst")).alias("edges")).withColumn("bytes", F.col("vertices") * 12 + F.col("edges") * 20)


def part_adjacency(blocks: DataFrame) -> DataFrame:
    """(a, b, edges): how many edges lead from one part to another."""
    return blocks.select(F.col("part_id").alias("a"), F.explode("dst_part").alias("b")).where("a <> b").groupBy("a", "b").agg(F.count("*").alias("edges"))


def mu_table(blocks: DataFrame, n_queries: int) -> DataFrame:
    """(part_id, mu): a part's edges by the number of queries, the unit of edge budgets."""
    return block_stats(blocks).select("part_id", F.round(F.col("edges") / n_queries, 6).alias("mu"))
