"""Partition plans: vertices (id, part_id), and how good they are."""

from __future__ import annotations

import heapq
import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from manyq.functions.ids import draw_order
from manyq.sources.graphs import Graph
from manyq.sources.tables import epoch


def partition_count(graph_bytes: float, block_bytes: float) -> int:
    """How many blocks of a size hold the graph."""
    return max(1, math.ceil(graph_bytes / block_bytes))


def global_rank(df: DataFrame, key: Column, *ties: Column, range_rows: int = 500_000) -> DataFrame:
    """df with `rank` from 0 by (key, ties), without one task seeing all rows: ranks within ranges of key, moved on by the ranges' counts.

    There are as many ranges as rows ask for; a key that many rows share is one range.
    """
    keyed = df.withColumn("_key", key.cast("double"))
    buckets = max(8, math.ceil(df.count() / range_rows))
    bounds = sorted(set(keyed.approxQuantile("_key", [i / buckets for i in range(1, buckets)], min(0.01, 0.2 / buckets))))
    ranged = keyed.withColumn("_range", F.size(F.filter(F.array(*map(F.lit, bounds)).cast("array<double>"), lambda b: b < F.col("_key"))))
    counts = ranged.groupBy("_range").count()  # a row per range
    moved = counts.select("_range", F.coalesce(F.sum("count").over(Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    own = F.row_number().over(Window.partitionBy("_range").orderBy("_key", *ties)) - 1
    return ranged.withColumn("_own", own).join(F.broadcast(moved), "_range").withColumn("rank", (F.col("_own") + F.col("_before")).cast("long")).drop("_key", "_range", "_own", "_before")


def partition_random(g: Graph, p: int, seed: int = 1) -> DataFrame:
    """Equal numbers of vertices, in an order that looks random."""
    ranked = global_rank(g.vertices, draw_order(F.col("id"), seed), F.col("id"))
    return ranked.select("id", F.floor(F.col("rank") * p / F.lit(g.n_vertices)).cast("int").alias("part_id"))


def partition_chunk(g: Graph, p: int, balance: str = "vertices", by: str = "ord") -> DataFrame:
    """Contiguous chunks of a vertex order with equal numbers of vertices, or of edges."""
    ranked = global_rank(g.vertices, F.col(by), F.col("id"))
    if balance == "vertices":
        return ranked.select("id", F.floor(F.col("rank") * p / F.lit(g.n_vertices)).cast("int").alias("part_id"))
    if balance != "edges":
        raise ValueError(balance)
    # Sums of degrees by slices of ranks first, so that no task runs over all vertices.
    sliced = ranked.withColumn("slice", F.floor(F.col("rank") * 64 / F.lit(g.n_vertices)).cast("int"))
    sums = sliced.groupBy("slice").agg(F.sum("deg").alias("s"))
    before = sums.select("slice", F.coalesce(F.sum("s").over(Window.orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    own = F.sum("deg").over(Window.partitionBy("slice").orderBy("rank").rowsBetween(Window.unboundedPreceding, -1))
    total = g.vertices.agg(F.sum("deg").alias("total"))
    placed = sliced.withColumn("own", F.coalesce(own, F.lit(0))).join(F.broadcast(before), "slice").join(F.broadcast(total))
    return placed.select("id", F.least(F.floor((F.col("own") + F.col("before")) * p / F.col("total")), F.lit(p - 1)).cast("int").alias("part_id"))


def partition_hash(g: Graph, p: int) -> DataFrame:
    return g.vertices.select("id", F.pmod(F.xxhash64("id"), F.lit(p)).cast("int").alias("part_id"))


def partition_range(g: Graph, p: int) -> DataFrame:
    """Equal ranges of ids."""
    ends = g.vertices.agg(F.min("id").alias("lo"), F.max("id").alias("hi"))
    return g.vertices.join(F.broadcast(ends)).select("id", F.expr(f"((id - lo) * {int(p)}) div (hi - lo + 1)").cast("int").alias("part_id"))


def partition_tiles(g: Graph, rows: int, columns: int, stride: int = 1_000_000) -> DataFrame:
    """A grid of tiles over vertices whose ord is row * stride + column."""
    xy = g.vertices.select("id", F.floor(F.col("ord") / stride).alias("x"), F.pmod("ord", F.lit(stride)).alias("y"))
    top = xy.agg((F.max("x") + 1).alias("nx"), (F.max("y") + 1).alias("ny"))
    at = xy.join(F.broadcast(top))
    return at.select("id", (F.floor(F.col("x") * rows / F.col("nx")) * columns + F.floor(F.col("y") * columns / F.col("ny"))).cast("int").alias("part_id"))


def cut_large(g: Graph, vparts: DataFrame, most_edges: int = 1_000_000, most_vertices: int = 250_000, slices: int = 32) -> DataFrame | None:
    """vparts with parts of more edges or vertices than a task should hold cut into ranges of the vertex order; None where all fit.

    A part's vertices fall into slices of about equal numbers, many for each piece, and neighbouring slices are taken together
    while they fit, so pieces are even in edges too; only a slice, in the end a single vertex, may exceed the bounds.
    """
    sized = vparts.join(g.vertices, "id").select("id", "part_id", "deg", "ord")
    known = sized.groupBy("part_id").agg(F.sum("deg").alias("edges"), F.count("*").alias("n")).collect()  # a row per part
    pieces = {r["part_id"]: max(math.ceil(r["edges"] / most_edges), math.ceil(r["n"] / most_vertices)) for r in known}
    if max(pieces.values(), default=1) <= 1:
        return None
    spark = g.pairs.sparkSession
    cuts = slices * max(pieces.values())
    large = F.col("part_id").isin([p for p, k in pieces.items() if k > 1])
    bounds = sized.where(large).groupBy("part_id").agg(F.percentile_approx("ord", [i / cuts for i in range(1, cuts)], 8 * cuts).alias("bounds")).collect()  # a row per part
    held = spark.createDataFrame([(r["part_id"], sorted(set(r["bounds"]))) for r in bounds], "part_id int, bounds array<long>")
    placed = sized.join(F.broadcast(held), "part_id", "left").withColumn("slice", F.coalesce(F.size(F.filter("bounds", lambda b: b < F.col("ord"))), F.lit(0))).drop("bounds")
    placed = epoch(placed, "slices")
    rows = placed.groupBy("part_id", "slice").agg(F.sum("deg").alias("edges"), F.count("*").alias("n")).orderBy("part_id", "slice").collect()  # a row per slice
    out, piece, now, edges, n = [], -1, None, 0, 0
    for r in rows:
        if r["part_id"] != now or pieces[now] > 1 and (edges + r["edges"] > most_edges or n + r["n"] > most_vertices):
            piece, now, edges, n = piece + 1, r["part_id"], 0, 0
        edges, n = edges + r["edges"], n + r["n"]
        out.append((r["part_id"], r["slice"], piece))
    piece_of = spark.createDataFrame(out, "part_id int, slice int, piece int")
    return placed.join(F.broadcast(piece_of), ["part_id", "slice"]).select("id", F.col("piece").alias("part_id"))


def partition_multilevel(g: Graph, p: int, levels: int = 64, imbalance: float = 0.2, sweeps: int = 2, coarse_rows: int = 4000) -> DataFrame:
    """Few edges across parts: merge neighbours level by level, split the small graph that is left, refine on the way back.

    Merging and refinement are joins and grouped sums; only the coarsest graph, of at most coarse_rows or 8 clusters a part, is
    split on the driver. A graph that does not shrink to that raises.
    """
    links = epoch(g.links.where("src < dst").select(F.col("src").alias("u"), F.col("dst").alias("v"), F.lit(1).cast("long").alias("w")), "cut")
    size = epoch(g.vertices.select(F.col("id").alias("u"), F.lit(1).cast("long").alias("size")), "size")
    maps: list[DataFrame] = []
    graphs = [(links, size)]
    most = max(1.0, g.n_vertices / p / 4)
    clusters = g.n_vertices
    for level in range(levels):
        if clusters <= max(coarse_rows // 4, 8 * p):
            break
        links, size = graphs[-1]
        mapping = epoch(_merge(links, size, most, level), "match")
        up = links.join(mapping.withColumnRenamed("c", "cu"), "u").join(mapping.select(F.col("u").alias("v"), F.col("c").alias("cv")), "v").where("cu <> cv")
        coarse = up.groupBy(F.least("cu", "cv").alias("u"), F.greatest("cu", "cv").alias("v")).agg(F.sum("w").alias("w"))
        merged = size.join(mapping, "u").groupBy("c").agg(F.sum("size").alias("size")).select(F.col("c").alias("u"), "size")
        maps.append(mapping)
        graphs.append((epoch(coarse, "cut"), epoch(merged, "size")))
        before, clusters = clusters, graphs[-1][1].count()
        if clusters > 0.98 * before:  # clusters are full, or have no links
            break
    if clusters > max(coarse_rows, 8 * p):
        raise ValueError(f"merging left {clusters} clusters, more than the driver splits")
    links, size = graphs[-1]
    plan = g.pairs.sparkSession.createDataFrame(_grow_parts(size.collect(), links.collect(), p), "u long, part_id int")
    plan = epoch(plan, "plan")
    for level in range(len(graphs) - 1, -1, -1):
        links, size = graphs[level]
        if level < len(graphs) - 1:
            plan = epoch(maps[level].join(plan.withColumnRenamed("u", "c"), "c").select("u", "part_id"), "plan")
        plan = _refine(plan, links, size, p, (1 + imbalance) * g.n_vertices / p, sweeps if level < len(graphs) - 1 else 1)
    return plan.select(F.col("u").alias("id"), "part_id")


def _merge(links: DataFrame, size: DataFrame, most: float, level: int) -> DataFrame:
    """(u, c): by a coin drawn anew at each level half of the clusters stay, and each other one joins the staying neighbour of its heaviest link.

    A cluster takes who comes with the heaviest links until it would exceed `most`; as each has a size of one or more, ranks
    beyond `most` cannot fit and go before the exchange.
    """
    stays = lambda name: F.pmod(F.xxhash64(F.lit(level), name), F.lit(2)) == 0
    both = links.unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v"), "w")).where(~stays("u") & stays("v"))
    # Equal weights are told apart by a hash, or low ids would gather all.
    choice = both.groupBy("u").agg(F.max(F.struct("w", F.xxhash64("u", "v", F.lit(level)).alias("h"), "v")).alias("s")).select("u", F.col("s.v").alias("v"), F.col("s.w").alias("w"))
    first = Window.partitionBy("v").orderBy(F.desc("w"), "u")
    near = choice.withColumn("r", F.row_number().over(first)).where(F.col("r") <= int(most)).drop("r")
    sized = near.join(size, "u").join(size.select(F.col("u").alias("v"), F.col("size").alias("own")), "v")
    held = F.sum("size").over(first.rowsBetween(Window.unboundedPreceding, 0)) + F.col("own")
    taken = sized.withColumn("held", held).where(F.col("held") <= most).select("u", F.col("v").alias("c"))
    return size.join(taken, "u", "left").select("u", F.coalesce("c", "u").alias("c"))


def _grow_parts(size: list, links: list, p: int) -> list[tuple[int, int]]:
    """Regions of equal weight over the small graph, grown by the cluster that most links lead to."""
    near: dict[int, list[tuple[int, int]]] = {r["u"]: [] for r in size}
    for r in links:
        near[r["u"]].append((r["w"], r["v"]))
        near[r["v"]].append((r["w"], r["u"]))
    weight = {r["u"]: r["size"] for r in size}
    total, out, part, held = sum(weight.values()), {}, 0, 0
    gain: dict[int, int] = {}
    open_: list[tuple[int, int]] = []  # (-gain, cluster); entries of a smaller gain than the cluster's own are stale
    left = iter(sorted(weight))
    while len(out) < len(weight):
        while open_ and (open_[0][1] in out or -open_[0][0] != gain[open_[0][1]]):
            heapq.heappop(open_)
        u = heapq.heappop(open_)[1] if open_ else next(x for x in left if x not in out)
        out[u] = part
        held += weight[u]
        for w, x in near[u]:
            if x not in out:
                gain[x] = gain.get(x, 0) + w
                heapq.heappush(open_, (-gain[x], x))
        if held >= total * (part + 1) / p and part < p - 1:
            part, gain, open_ = part + 1, {}, []
    return sorted(out.items())


def _refine(plan: DataFrame, links: DataFrame, size: DataFrame, p: int, cap: float, sweeps: int) -> DataFrame:
    """Move border vertices to the part that most of their links go to, while it has room; parts take turns by parity so that neighbours do not swap."""
    both = links.unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v"), "w"))
    for sweep in range(sweeps):
        pull = both.join(plan.select(F.col("u").alias("v"), F.col("part_id").alias("to")), "v").groupBy("u", "to").agg(F.sum("w").alias("w"))
        best = pull.join(plan, "u").join(size, "u")
        own = best.where("to = part_id").select("u", F.col("w").alias("own"))
        up = F.col("to") > F.col("part_id") if sweep % 2 == 0 else F.col("to") < F.col("part_id")
        gain = best.where(up).join(own, "u", "left").withColumn("gain", F.col("w") - F.coalesce("own", F.lit(0))).where("gain > 0")
        move = gain.withColumn("r", F.row_number().over(Window.partitionBy("u").orderBy(F.desc("gain"), "to"))).where("r = 1")
        load = plan.join(size, "u").groupBy("part_id").agg(F.sum("size").alias("load")).withColumnRenamed("part_id", "to")
        room = Window.partitionBy("to").orderBy(F.desc("gain"), "u").rowsBetween(Window.unboundedPreceding, 0)
        taken = move.join(F.broadcast(load), "to", "left").withColumn("s", F.sum("size").over(room) + F.coalesce("load", F.lit(0))).where(F.col("s") <= cap)
        plan = epoch(plan.join(taken.select("u", "to"), "u", "left").select("u", F.coalesce("to", "part_id").alias("part_id")), "plan")
    return plan


def partition_quality(g: Graph, vparts: DataFrame) -> DataFrame:
    """One row: edges, cut_edges, cut_ratio, parts, largest, boundary (vertices with a cut edge)."""
    e = g.links.join(vparts.select(F.col("id").alias("src"), F.col("part_id").alias("a")), "src").join(vparts.select(F.col("id").alias("dst"), F.col("part_id").alias("b")), "dst")
    cut = F.col("a") != F.col("b")
    counts = e.agg(F.count("*").alias("edges"), F.count_if(cut).alias("cut_edges"), F.count_distinct(F.when(cut, F.col("src"))).alias("boundary"))
    parts = vparts.groupBy("part_id").count().agg(F.count("*").alias("parts"), F.max("count").alias("largest"))
    return counts.join(parts).select("edges", "cut_edges", F.round(F.col("cut_edges") / F.col("edges"), 6).alias("cut_ratio"), "parts", "largest", "boundary")


def graph_stats(g: Graph) -> DataFrame:
    """One row: n_vertices, n_edges, average degree, largest degree, bytes of the block form."""
    return g.vertices.agg(F.count("*").alias("n_vertices"), F.sum("deg").cast("long").alias("n_edges"), F.max("deg").alias("max_deg")).select(
        "n_vertices", "n_edges", F.round(F.col("n_edges") / F.col("n_vertices"), 4).alias("avg_deg"), "max_deg", (F.col("n_vertices") * 12 + F.col("n_edges") * 20).cast("long").alias("bytes")
    )
