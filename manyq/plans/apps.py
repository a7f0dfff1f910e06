"""Applications of fork batches: betweenness centrality, community profiles, landmark labels, walk features, ant colonies."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from manyq.operators.blocks import BlockedGraph, blocked, pack_blocks
from manyq.operators.seeds import all_sources
from manyq.plans.engine import run_waves
from manyq.plans.kernels import Countdown
from manyq.plans.policy import Policy
from manyq.plans.queries import multi_bfs, multi_sssp, multi_walk
from manyq.sources.graphs import Graph
from manyq.sources.tables import epoch


# Betweenness centrality


def shortest_dag(bg: BlockedGraph, lengths: DataFrame, weighted: bool) -> DataFrame:
    """(query_id, u, v, u_part, v_part): the edges on shortest ways, from (query_id, v, dist)."""
    step = F.col("w") if weighted else F.lit(1)
    edges = bg.graph.edges
    a = lengths.select("query_id", F.col("v").alias("src"), F.col("dist").alias("du"))
    b = lengths.select("query_id", F.col("v").alias("dst"), F.col("dist").alias("dv"))
    dag = a.join(edges, "src").join(b, ["query_id", "dst"]).where(F.col("dv") == F.col("du") + step)
    part = lambda name, to: bg.vparts.select(F.col("id").alias(name), F.col("part_id").alias(to))
    return dag.join(part("src", "u_part"), "src").join(part("dst", "v_part"), "dst").select("query_id", F.col("src").alias("u"), F.col("dst").alias("v"), "u_part", "v_part")


def _count_down(dag: DataFrame, nodes: DataFrame, starts: DataFrame, kernel: Countdown, n: int) -> DataFrame:
    """(query_id, v, total): sums along dag (query_id, u, v, u_part, v_part); nodes (query_id, v, part_id, factor, and first, what the sum begins with, if not 0); starts (query_id, v, give)."""
    awaited = dag.groupBy("query_id", "v").agg(F.count("*").alias("aux"))
    state = nodes.join(awaited, ["query_id", "v"], "left").join(starts, ["query_id", "v"], "left")
    first = F.col("first") if "first" in nodes.columns else F.lit(0.0)
    state = epoch(state.select("part_id", F.lit(0).alias("bucket"), "query_id", "v", first.alias("num"), F.coalesce("aux", F.lit(0)).cast("long").alias("aux"), "give", F.col("factor").alias("rest")), "nodes")
    ops = state.where("aux = 0").select("part_id", "bucket", "query_id", "v", F.coalesce("give", F.lit(0.0)).alias("num"), F.lit(0).cast("long").alias("aux"), F.lit(0).cast("long").alias("aux2"), F.lit(0.0).alias("prio"), F.lit(0).cast("long").alias("seq"))
    held = state.select("part_id", "bucket", "query_id", "v", "num", "aux", F.lit(0).cast("long").alias("aux2"), "rest")
    sides = epoch(dag.select(F.col("u_part").alias("part_id"), "query_id", "u", "v", "v_part").unionByName(nodes.select("part_id").distinct().select("part_id", F.lit(-1).alias("query_id"), F.lit(-1).cast("long").alias("u"), F.lit(-1).cast("long").alias("v"), F.lit(-1).alias("v_part"))), "dag")
    r = run_waves(ops, held, sides, kernel, Policy.fifo(), n, uuid.uuid4().hex)
    return r.state.select("query_id", "v", F.col("num").alias("total"))


def betweenness(bg: BlockedGraph, sources: DataFrame, weighted: bool = False, scale: bool = True, policy: Policy | None = None) -> DataFrame:
    """(v, score): dependencies summed over the sources, scaled by vertices over sources where these are a sample."""
    n = sources.count()
    _, own = _dependencies(bg, sources, weighted, policy)
    factor = bg.graph.n_vertices / n if scale else 1.0
    scores = own.groupBy("v").agg((F.sum("give") * factor).alias("score"))
    return bg.graph.vertices.select(F.col("id").alias("v")).join(scores, "v", "left").select("v", F.coalesce("score", F.lit(0.0)).alias("score"))


def _dependencies(bg: BlockedGraph, sources: DataFrame, weighted: bool, policy: Policy | None = None, mass: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """Lengths (query_id, v, dist), and (query_id, v, give): each source's dependency on the vertices it reaches, itself left out. mass: (v, mass), how many vertices one stands for as an end."""
    n = sources.count()
    lengths = multi_sssp(bg, sources, policy=policy).select("query_id", "v", "dist") if weighted else multi_bfs(bg, sources, policy=policy).select("query_id", "v", F.col("level").alias("dist"))
    lengths = epoch(lengths, "lengths")
    dag = epoch(shortest_dag(bg, lengths, weighted), "dag")
    nodes = lengths.join(bg.vparts.withColumnRenamed("id", "v"), "v").select("query_id", "v", "part_id", F.lit(1.0).alias("factor"))
    starts = sources.select("query_id", F.col("src").alias("v"), F.lit(1.0).alias("give"))
    ways = epoch(_count_down(dag, nodes, starts, Countdown(), n), "ways")
    back = dag.select("query_id", F.col("v").alias("u"), F.col("u").alias("v"), F.col("v_part").alias("u_part"), F.col("u_part").alias("v_part"))
    weighed = nodes.drop("factor").join(ways.withColumnRenamed("total", "factor"), ["query_id", "v"])
    extra = F.lit(0.0)
    if mass is not None:  # a fired vertex passes on (1 + factor * sum) / factor: a sum that begins so passes on mass for 1
        extra = F.col("mass") - 1.0
        weighed = weighed.join(mass, "v").withColumn("first", extra / F.col("factor")).drop("mass")
    none = starts.select("query_id", "v", F.lit(0.0).alias("give")).where("false")
    sums = _count_down(back, weighed, none, Countdown(backward=True), n)
    own = sums.join(ways.withColumnRenamed("total", "ways"), ["query_id", "v"]).join(sources.select("query_id", F.col("src").alias("v")), ["query_id", "v"], "left_anti")
    own = own if mass is None else own.join(mass, "v")
    return lengths, own.select("query_id", "v", (F.col("total") * F.col("ways") - extra).alias("give"))


def fold_pendants(g: Graph, rounds: int = 32) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(folded, mass, links) of an undirected graph whose vertices with one neighbour are folded into it, round by round.

    folded: (v, parent, size, round), size the vertices that v then stood for. mass: (v, mass) of what is left, links between
    it. Of two vertices that have only each other the larger folds. Any number of rounds is right; what is left has no
    pendants unless rounds ran out.
    """
    links = epoch(g.links, "links")
    mass = epoch(g.vertices.select(F.col("id").alias("v"), F.lit(1).cast("long").alias("mass")), "mass")
    folded = None
    for i in range(rounds):
        one = links.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("deg"), F.min("dst").alias("parent")).where("deg = 1").select("v", "parent")
        back = one.select(F.col("v").alias("parent"), F.col("parent").alias("v"), F.lit(True).alias("mutual"))
        leaf = one.join(back, ["v", "parent"], "left").where("mutual IS NULL OR v > parent").select("v", "parent")
        leaf = epoch(leaf.join(mass, "v").select("v", "parent", F.col("mass").alias("size"), F.lit(i).alias("round")), "folded")
        if leaf.isEmpty():
            break
        folded = leaf if folded is None else folded.unionByName(leaf)
        more = leaf.groupBy(F.col("parent").alias("v")).agg(F.sum("size").alias("more"))
        gone = leaf.select("v")
        mass = epoch(mass.join(gone, "v", "left_anti").join(more, "v", "left").select("v", (F.col("mass") + F.coalesce("more", F.lit(0))).alias("mass")), "mass")
        links = epoch(links.join(gone.withColumnRenamed("v", "src"), "src", "left_anti").join(gone.withColumnRenamed("v", "dst"), "dst", "left_anti"), "links")
    if folded is None:
        folded = leaf
    return folded, mass, links


def betweenness_exact(bg: BlockedGraph, weighted: bool = False, batch: int = 256) -> DataFrame:
    """(v, score) from all vertices, as ends of ways in both directions.

    Pendant trees of an undirected graph are folded first: ways into them have no choice, so their pairs are counted, by the
    sizes of the branches at a vertex. The queries run between the vertices that are left, each with the mass it stands for,
    `batch` at a time.
    """
    g = bg.graph
    if g.directed:
        return betweenness(bg, all_sources(g), weighted)
    folded, mass, links = fold_pendants(g)
    core = Graph(g.pairs, g.orders, False, g.unit, f"{g.name}-core")
    core.__dict__["links"] = links
    core.__dict__["edges"] = epoch(g.edges.join(links, ["src", "dst"], "left_semi"), "edges")  # with the weights of the whole graph
    core._cache["own_edges"] = True
    linked = links.groupBy(F.col("src").alias("v")).count().select("v")
    size = mass.join(linked, "v", "left_anti").select("v", F.col("mass").alias("n"))  # components that are folded whole
    gives = None
    n_core = linked.count()
    if n_core:
        vparts = epoch(bg.vparts.join(linked.withColumnRenamed("v", "id"), "id", "left_semi"), "vparts")
        rest = BlockedGraph(core, vparts, epoch(pack_blocks(core, vparts), "blocks"), bg.n_parts)
        everyone = epoch(all_sources(core), "sources")
        for lo in range(0, n_core, batch):
            own = everyone.where((F.col("query_id") >= lo) & (F.col("query_id") < lo + batch))
            lengths, give = _dependencies(rest, own, weighted, mass=mass)
            home = own.join(mass.withColumnRenamed("v", "src"), "src").select("query_id", "src", F.col("mass").alias("by"))
            size = size.unionByName(lengths.join(mass, "v").groupBy("query_id").agg(F.sum("mass").alias("n")).join(own, "query_id").select(F.col("src").alias("v"), "n"))
            here = epoch(give.join(home, "query_id").groupBy("v").agg(F.sum(F.col("give") * F.col("by")).alias("give")), "gives")
            gives = here if gives is None else epoch(gives.unionByName(here).groupBy("v").agg(F.sum("give").alias("give")), "gives")
    size = epoch(size, "sizes")
    for r in range(folded.agg(F.max("round")).first()[0] if not folded.isEmpty() else -1, -1, -1):
        down = folded.where(F.col("round") == r).select("v", "parent")
        size = epoch(size.unionByName(down.join(size.withColumnRenamed("v", "parent"), "parent").select("v", "n")), "sizes")
    # Ordered pairs of a vertex's branches: all pairs of the other vertices without those inside one branch.
    k = F.col("size").cast("double")
    branches = folded.groupBy(F.col("parent").alias("v")).agg(F.sum(k).alias("below"), F.sum(k * k).alias("inside"))
    others, below = F.col("n").cast("double") - 1.0, F.coalesce("below", F.lit(0.0))
    scores = size.join(branches, "v", "left").withColumn("score", others * others - F.coalesce("inside", F.lit(0.0)) - (others - below) * (others - below))
    if gives is not None:
        scores = scores.join(gives, "v", "left").withColumn("score", F.col("score") + F.coalesce("give", F.lit(0.0)))
    return scores.select("v", "score")


# Network community profile


def sweep(g: Graph, ranks: DataFrame, max_size: int | None = None) -> DataFrame:
    """(query_id, size, conductance): of the prefixes of vertices by falling p / degree, ties by id; ranks: (query_id, v, p)."""
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "v")
    placed = ranks.join(g.vertices.select(F.col("id").alias("v"), "deg"), "v").withColumn("score", F.round(F.col("p") / F.col("deg"), 12)).withColumn("size", F.row_number().over(order))
    placed = epoch((placed if max_size is None else placed.where(F.col("size") <= max_size)).select("query_id", "v", "deg", "size"), "placed")
    a = placed.select("query_id", F.col("v").alias("src"), F.col("size").alias("a"))
    b = placed.select("query_id", F.col("v").alias("dst"), F.col("size").alias("b"))
    inner = a.join(g.links, "src").join(b, ["query_id", "dst"]).groupBy("query_id", F.greatest("a", "b").alias("size")).agg(F.count("*").alias("inside"))
    prefix = Window.partitionBy("query_id").orderBy("size").rowsBetween(Window.unboundedPreceding, 0)
    both = placed.join(inner, ["query_id", "size"], "left").withColumn("volume", F.sum("deg").over(prefix)).withColumn("inside", F.sum(F.coalesce("inside", F.lit(0))).over(prefix))
    total = g.vertices.agg(F.sum("deg").alias("total"))
    small = F.least(F.col("volume"), F.col("total") - F.col("volume"))
    return both.join(F.broadcast(total)).select("query_id", "size", F.when(small > 0, (F.col("volume") - F.col("inside")) / small).alias("conductance"))


def best_cut(swept: DataFrame) -> DataFrame:
    """(query_id, size, conductance): each query's best prefix, the smaller of equals."""
    least = F.min(F.struct(F.round("conductance", 9).alias("conductance"), "size")).alias("s")
    return swept.where("conductance IS NOT NULL").groupBy("query_id").agg(least).select("query_id", "s.size", "s.conductance")


def community_profile(swept: DataFrame) -> DataFrame:
    """(size, conductance): the least conductance found for each size."""
    return swept.where("conductance IS NOT NULL").groupBy("size").agg(F.min("conductance").alias("conductance"))


# Landmark labels


def label_vertices(bg: BlockedGraph, landmarks: DataFrame, weighted: bool = True, policy: Policy | None = None) -> DataFrame:
    """(v, landmark, dist)."""
    if weighted:
        found = multi_sssp(bg, landmarks, policy=policy)
    else:
        found = multi_bfs(bg, landmarks, policy=policy).withColumnRenamed("level", "dist")
    return found.join(F.broadcast(landmarks), "query_id").select("v", F.col("src").alias("landmark"), "dist")


def label_query(labels: DataFrame, pairs: DataFrame) -> DataFrame:
    """(a, b, upper, lower): bounds of the distances of pairs (a, b) from common landmarks."""
    la = labels.select(F.col("v").alias("a"), "landmark", F.col("dist").alias("da"))
    lb = labels.select(F.col("v").alias("b"), "landmark", F.col("dist").alias("db"))
    return pairs.join(la, "a").join(lb, ["b", "landmark"]).groupBy("a", "b").agg(F.min(F.col("da") + F.col("db")).alias("upper"), F.max(F.abs(F.col("da") - F.col("db"))).alias("lower"))


def folded(labels: DataFrame) -> DataFrame:
    """(v, labels map<landmark, dist>)."""
    return labels.groupBy("v").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("landmark", "dist")))).alias("labels"))


def pruned_labels(bg: BlockedGraph, landmarks: DataFrame, batch: int, weighted: bool = True) -> DataFrame:
    """Labels in batches of landmarks, in query order; a label that earlier ones already answer is dropped."""
    kept = None
    n = landmarks.count()
    for lo in range(0, n, batch):
        own = landmarks.where((F.col("query_id") >= lo) & (F.col("query_id") < lo + batch))
        fresh = label_vertices(bg, own, weighted)
        if kept is not None:
            to = kept.join(F.broadcast(own.select(F.col("src").alias("v"), F.col("src").alias("target"))), "v").select("landmark", "target", F.col("dist").alias("dt"))
            cover = kept.join(to, "landmark").groupBy("v", F.col("target").alias("landmark")).agg(F.min(F.col("dist") + F.col("dt")).alias("known"))
            fresh = fresh.join(cover, ["v", "landmark"], "left").where("known IS NULL OR known > dist").select("v", "landmark", "dist")
        kept = epoch(fresh if kept is None else kept.unionByName(fresh), "labels")
    return kept


# Walks


def walk_pairs(walks: DataFrame, window: int) -> DataFrame:
    """(a, b, n): how often b comes within so many steps after a in one walk."""
    b = walks.select("query_id", "walk", F.col("step").alias("t"), F.col("v").alias("b"))
    near = walks.select("query_id", "walk", "step", F.col("v").alias("a")).join(b, ["query_id", "walk"]).where((F.col("t") > F.col("step")) & (F.col("t") <= F.col("step") + window))
    return near.groupBy("a", "b").agg(F.count("*").alias("n"))


def ant_colony(g: Graph, sources: DataFrame, rounds: int = 3, length: int = 8, ants: int = 4, evaporation: float = 0.5, parts: int = 4) -> DataFrame:
    """(src, dst, pheromone): each round's ants walk by pheromone, which then evaporates and is renewed along their ways; short ways give more."""
    base = epoch(g.edges.select("src", "dst", "w", F.lit(100.0).alias("pheromone")), "pheromone")
    for i in range(rounds):
        weighed = Graph(g.pairs, g.orders, g.directed, g.unit, f"{g.name}-ants{i}")
        weighed._cache["own_edges"] = True
        weighed.__dict__["edges"] = base.select("src", "dst", F.greatest(F.lit(1), F.col("pheromone").cast("long")).alias("w"))
        bg = blocked(weighed, parts=parts)
        walks = multi_walk(bg, sources, length, ants, bias="weight", seed=i)
        nxt = Window.partitionBy("query_id", "walk").orderBy("step")
        moves = walks.withColumn("dst", F.lead("v").over(nxt)).where("dst IS NOT NULL").select("query_id", "walk", F.col("v").alias("src"), "dst")
        cost = moves.join(g.edges, ["src", "dst"]).withColumn("cost", F.sum("w").over(Window.partitionBy("query_id", "walk")))
        deposit = cost.groupBy("src", "dst").agg(F.sum(1000.0 / F.col("cost")).alias("d"))
        base = epoch(base.join(deposit, ["src", "dst"], "left").select("src", "dst", "w", (F.col("pheromone") * (1 - evaporation) + F.coalesce("d", F.lit(0.0))).alias("pheromone")), "pheromone")
    return base.select("src", "dst", "pheromone")
