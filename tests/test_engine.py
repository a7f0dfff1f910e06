import heapq
import math
import random
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import Row
from pyspark.sql import functions as F

from manyq import workloads
from manyq.operators import measures, partition, seeds
from manyq.operators.blocks import BlockedGraph, blocked, pack_blocks, unpack_blocks
from manyq.plans import apps, baselines, engine, queries, turns, vector
from manyq.plans.engine import fork
from manyq.plans.kernels import LocalGraph, Push, Relax
from manyq.plans.policy import Pending, Policy, YieldPolicy, policy_ladder
from manyq.sources.graphs import Graph, reached, settled
from manyq.streaming import requests
from tests import fixtures as fx

ONE = Policy(wave_width=1)


def graph(spark, pairs, **more):
    return Graph(spark.createDataFrame(pairs, "x long, y long"), **more)


def test_yielding_keeps_the_answer_and_does_less_work(spark):
    bg = fx.build(spark, *fx.YIELDING)
    plain = fork(bg, fx.sources(spark, "A"), Relax(True), ONE)
    paused = fork(bg, fx.sources(spark, "A"), Relax(True), ONE.but(pause=YieldPolicy(delta=3)))
    assert fx.lengths(plain) == fx.lengths(paused) == {0: "A0 B1 C2 D2 E3 F4 H3"}
    assert (plain.total("edges"), paused.total("edges")) == (18, 14)
    assert paused.trace[0][6:8] == (1, 1)  # H is kept, D is sent


def test_two_queries_whatever_the_schedule(spark):
    bg = fx.build(spark, *fx.TWO_QUERIES)
    want = {0: "A0 B1 C1 D2 E3 F4 G5 H6 I3 J2 K3 L4 M5 N6 O7", 1: "A3 B2 C4 D3 E4 F5 G6 H7 I0 J1 K2 L3 M4 N5 O6"}
    policies = [Policy(buckets=2), ONE.but(scheduler="max_ops", pause=YieldPolicy(delta=2)), Policy(scheduler="random", wave_width=2), *policy_ladder(YieldPolicy(delta=2)).values()]
    for p in policies:
        assert fx.lengths(fork(bg, fx.sources(spark, "AI"), Relax(True), p)) == want


def test_blocks_of_dropped_graphs_are_never_reused(spark):
    """Two graphs of one name, wrapped and dropped by turns: a worker's decoded blocks must not outlive their graph's token."""
    made = [blocked(graph(spark, pairs, unit=True), parts=2) for pairs in ([(i, i + 1) for i in range(5)], [(0, i) for i in range(1, 6)])]
    src = spark.createDataFrame([(0, 0)], "query_id int, src long")
    want = [{i: i for i in range(6)}, {i: min(i, 1) for i in range(6)}]
    for turn in range(20):
        m = made[turn % 2]
        bg = BlockedGraph(m.graph, m.vparts, m.blocks, m.n_parts)
        assert {r["v"]: r["level"] for r in queries.multi_bfs(bg, src).collect()} == want[turn % 2]
        del bg


def test_priority_schedule_is_not_worse(spark):
    bg = fx.build(spark, *fx.SCHEDULES)
    visits = {}
    for name in ("priority", "fifo", "max_ops", "random"):
        r = fork(bg, fx.sources(spark, "AC"), Relax(True), ONE.but(scheduler=name, pause=YieldPolicy(delta=2)))
        visits[name] = (len(r.trace), r.total("edges"))
    assert min(visits.values()) == visits["priority"], visits


def test_tiny_budgets_still_end(spark):
    bg = fx.build(spark, *fx.YIELDING)
    r = fork(bg, fx.sources(spark, "A"), Relax(True), Policy(pause=YieldPolicy(edges=0.0)))
    assert fx.lengths(r)[0] == "A0 B1 C2 D2 E3 F4 H3"


def test_unfinished_runs_raise(spark):
    bg = fx.build(spark, *fx.YIELDING)
    with pytest.raises(RuntimeError):
        fork(bg, fx.sources(spark, "A"), Relax(True), max_waves=1)
    with pytest.raises(ValueError):
        fork(bg, fx.sources(spark, "Z"), Relax(True))


def test_schedulers_order_parts():
    pending = [Pending(0, 5.0, 3, 10), Pending(1, 2.0, 9, 4), Pending(2, 7.0, 1, 99)]
    first = {s: Policy(scheduler=s, wave_width=1).choose(pending, 1)[0] for s in ("priority", "fifo", "max_ops")}
    assert first == {"priority": 1, "fifo": 2, "max_ops": 2}
    assert Policy(window=3.0).choose(pending, 1) == [1, 0]
    assert Policy(scheduler=lambda p, wave: (p.ops,)).choose(pending, 1) == [1, 0, 2]


@pytest.mark.parametrize("most", [100, 8])
def test_turns_answer_alike_in_fewer_waves(spark, monkeypatch, most):
    """All parts in one task, and two or so in each; with pauses, and operations split among tasks."""
    monkeypatch.setattr(turns, "MOST_VERTICES", most)
    bg = fx.build(spark, *fx.TWO_QUERIES)
    src = fx.sources(spark, "AI")
    want = {0: "A0 B1 C1 D2 E3 F4 G5 H6 I3 J2 K3 L4 M5 N6 O7", 1: "A3 B2 C4 D3 E4 F5 G6 H7 I0 J1 K2 L3 M4 N5 O6"}
    for p in (Policy(pause=YieldPolicy(delta=1)), policy_ladder(YieldPolicy(delta=2))["buffer"]):
        traced = fork(bg, src, Relax(True), p.but(turns=True))
        assert fx.lengths(traced) == fx.lengths(fork(bg, src, Relax(True), p.but(turns=True), traced=False)) == want
        assert (traced.waves == 1) == (most == 100)
    mass = fork(bg, src, Push(0.15, 1e-5), Policy.ppr(0.5).but(turns=True)).state.collect()
    assert sum(x["num"] + x["rest"] for x in mass) == pytest.approx(2.0, abs=1e-9)  # also where all state was written whole in the last wave


def test_turns_run_queries_in_batches(spark, monkeypatch):
    """More queries than tasks may hold at once run one batch after another, and none is lost."""
    monkeypatch.setattr(turns, "MOST_ENTRIES", 15)
    bg = fx.build(spark, *fx.TWO_QUERIES)
    assert turns.shares(15 * 70, 1, 15, Policy())[0] > 1
    monkeypatch.setattr(turns, "shares", lambda n, hosts, largest, policy: (3, 2))
    src = fx.sources(spark, "ABCDEFGHIJKLMNO")
    assert fx.lengths(fork(bg, src, Relax(True), Policy(turns=True), traced=False)) == fx.lengths(fork(bg, src, Relax(True)))


def test_other_kernels_agree_with_the_single_part(spark):
    bg = fx.build(spark, *fx.YIELDING)
    one = fx.build(spark, fx.YIELDING[0], {0: "ABCDEFH"}, "single")
    src = fx.sources(spark, "AE")
    for make in (lambda b: queries.multi_dfs(b, src), lambda b: queries.multi_walk(b, src, 5, 3), lambda b: queries.multi_walk(b, src, 5, 3, restart=0.3, bias="weight"), lambda b: queries.multi_kshortest(b, src, 3)):
        assert sorted(map(tuple, make(bg).collect())) == sorted(map(tuple, make(one).collect()))


def test_shortest_walks_against_brute_force(spark):
    bg = fx.build(spark, *fx.YIELDING)
    links = {}
    for r in bg.graph.edges.collect():
        links.setdefault(r["src"], []).append(r["dst"])
    found, heap = {}, [(0, ord("A"))]
    while heap:
        d, v = heapq.heappop(heap)
        if len(found.setdefault(v, [])) < 3:
            found[v].append(d)
            for u in links[v]:
                heapq.heappush(heap, (d + 1, u))
    got = queries.multi_kshortest(bg, fx.sources(spark, "A"), 3).collect()
    assert {(r["v"], r["rank"]): r["dist"] for r in got} == {(v, i): d for v, own in found.items() for i, d in enumerate(own)}


def test_pagerank_closed_form_and_mass(spark):
    bg = blocked(graph(spark, [(1, 2)]), parts=2)
    src = spark.createDataFrame([(0, 1)], "query_id int, src long")
    p = {r["v"]: r["p"] for r in queries.multi_ppr(bg, src, 0.15, 1e-10).collect()}
    assert p[1] == pytest.approx(1 / 1.85, abs=1e-8) and p[2] == pytest.approx(0.85 / 1.85, abs=1e-8)
    bg = fx.build(spark, *fx.YIELDING)
    r = fork(bg, fx.sources(spark, "A"), Push(0.15, 1e-5), Policy.ppr(0.5)).state.collect()
    assert sum(x["num"] + x["rest"] for x in r) == pytest.approx(1.0, abs=1e-9)


def test_betweenness_closed_forms(spark):
    star = apps.betweenness_exact(blocked(graph(spark, [(0, i) for i in range(1, 6)]), parts=2))
    assert {r["v"]: round(r["score"], 6) for r in star.collect()} == {0: 20.0} | dict.fromkeys(range(1, 6), 0.0)
    path = apps.betweenness_exact(blocked(graph(spark, [(i, i + 1) for i in range(5)], unit=True), parts=3), weighted=True)
    assert {r["v"]: round(r["score"], 6) for r in path.collect()} == {i: 2.0 * i * (5 - i) for i in range(6)}


def test_best_cut_of_two_cliques(spark):
    k = 5
    pairs = [(a + s, b + s) for s in (0, 10) for a in range(k) for b in range(a)] + [(0, 10)]
    g = graph(spark, pairs)
    src = spark.createDataFrame([(0, 1)], "query_id int, src long")
    best = apps.best_cut(apps.sweep(g, queries.multi_ppr(blocked(g, parts=2), src, eps=1e-8))).first()
    assert best["size"] == k and best["conductance"] == pytest.approx(1 / (k * (k - 1) + 1))


def test_degenerate_graphs(spark):
    g = graph(spark, [(1, 2), (2, 1), (3, 3), (4, 5), (1, 2)])
    assert g.links.count() == 4 and g.n_vertices == 4  # a loop is no edge
    bg = blocked(g, parts=4)
    src = spark.createDataFrame([(0, 1), (1, 1), (2, 5)], "query_id int, src long")
    got = sorted((r["query_id"], r["v"], int(r["num"])) for r in fork(bg, src, Relax(False)).state.collect())
    assert got == [(0, 1, 0), (0, 2, 1), (1, 1, 0), (1, 2, 1), (2, 4, 1), (2, 5, 0)]
    assert sorted(map(tuple, unpack_blocks(bg.blocks).select("src", "dst", "w").collect())) == sorted(map(tuple, g.edges.collect()))


def test_baselines_agree(spark):
    bg = fx.build(spark, *fx.TWO_QUERIES)
    g, src = bg.graph, fx.sources(spark, "AI")
    want = sorted(map(tuple, queries.multi_sssp(bg, src).collect()))
    for r in (baselines.frontier_run(g, src, True), baselines.bsp_run(g, src, True), baselines.segmented_run(g, src, True)):
        assert sorted(map(tuple, r.state.select("query_id", "v", "dist", "pred").collect())) == want
    assert sorted(tuple(r)[:4] for r in baselines.inter_query_run(g, src, True).collect()) == want
    one = fx.sources(spark, "A")
    levels = sorted(map(tuple, queries.multi_bfs(bg, one).collect()))
    for d in ("pull", "auto"):
        assert sorted(map(tuple, baselines.frontier_run(g, one, False, d).state.select("query_id", "v", "dist", "pred").collect())) == levels


def test_measures_and_published_arithmetic():
    assert measures.cache_model([1, 2, 1, 3, 2, 1], 2) == (6, 5)
    assert round(measures.cpu_inflation(10, 1.59, 8.39), 2) == 1.90 and round(measures.cpu_inflation(10, 6.75, 46.74), 2) == 1.44
    sizes = {1.65e9: 120, 1.37e9: 100, 0.54e9: 40, 1.04e9: 76, 0.50e9: 37, 17.27e9: 1256}
    assert all(partition.partition_count(b, 13.75e6) == n for b, n in sizes.items())


def test_partition_plans_cover(spark):
    g = graph(spark, [(i, (i * 7 + 3) % 40) for i in range(40)] + [(i, i + 1) for i in range(39)])
    for plan in (partition.partition_random(g, 4), partition.partition_chunk(g, 4), partition.partition_chunk(g, 4, "edges"), partition.partition_hash(g, 4), partition.partition_multilevel(g, 4)):
        rows = plan.collect()
        assert sorted(r["id"] for r in rows) == list(range(40)) and {r["part_id"] for r in rows} <= set(range(4))
    assert seeds.sample_sources(g, 5).count() == 5


def test_merging_keeps_clusters_small(spark):
    hub = [(0, v, 1) for v in range(1, 301)] + [(1, 2, 5)]  # a hub that all would join, and a pair with a heavier link
    links, size = spark.createDataFrame(hub, "u long, v long, w long"), spark.range(302).selectExpr("id AS u", "1L AS size")
    for level in range(4):
        merged = {r.u: r.c for r in partition._merge(links, size, 10.0, level).collect()}
        assert set(merged) == set(range(302)) and merged[301] == 301  # a vertex without links stays alone
        assert all(merged[c] == c for c in merged.values()) and max(Counter(merged.values()).values()) <= 10


def test_grown_parts_are_even_and_whole(spark):
    size = [Row(u=u, size=1) for u in range(40)]
    links = [Row(u=u, v=u + 1, w=1) for u in range(38)]  # a path, and a vertex alone
    plan = dict(partition._grow_parts(size, links, 4))
    assert sorted(plan) == list(range(40)) and Counter(plan.values()) == {0: 10, 1: 10, 2: 10, 3: 10}
    assert sum(plan[u] != plan[u + 1] for u in range(38)) <= 4


def test_registered_profile_has_all_sizes(spark, monkeypatch):
    """Every size that 16 pushes reach is in the profile, not the first few hundred."""
    seen = []
    swept = workloads.apps.sweep
    monkeypatch.setattr(workloads.apps, "sweep", lambda g, ranks, *a: seen.append((g, ranks.cache())) or swept(g, seen[0][1], *a))
    got = workloads.queries()["ncp_pushed"](spark, "/root/testdata/sf0.01")
    sizes = {r["size"] for r in got.collect()}
    (g, ranks), = seen
    reached = [r["count"] for r in ranks.groupBy("query_id").count().collect()]
    assert len(reached) == 16 and max(reached) > 400
    # A sweep over all vertices of the graph has no conductance.
    assert sizes == set(range(1, min(max(reached), g.n_vertices - 1) + 1))


def _brandes(links: dict, sources: list, weighted: bool) -> dict:
    score = dict.fromkeys(links, 0.0)
    for s in sources:
        dist, done, heap = {s: 0}, [], [(0, s)]
        while heap:
            d, u = heapq.heappop(heap)
            if d > dist[u]:
                continue
            done.append(u)
            for v, w in links[u]:
                if d + (w if weighted else 1) < dist.get(v, math.inf):
                    dist[v] = d + (w if weighted else 1)
                    heapq.heappush(heap, (dist[v], v))
        order = list(dict.fromkeys(done))
        before = {v: [u for u, w in links[v] if u in dist and dist[u] + (w if weighted else 1) == dist[v]] for v in order}
        ways, give = {s: 1.0}, dict.fromkeys(order, 0.0)
        for v in order[1:]:
            ways[v] = sum(ways[u] for u in before[v])
        for v in order[:0:-1]:
            for u in before[v]:
                give[u] += ways[u] / ways[v] * (1 + give[v])
            score[v] += give[v]
    return {v: x * len(links) / len(sources) for v, x in score.items()}


@pytest.mark.parametrize("weighted", [False, True])
def test_exact_betweenness_folds_pendants(spark, weighted):
    """Cycles with trees hanging on them, a component that is a tree, and one of two vertices; no more queries than the cycles have vertices."""
    pairs = [(0, 1), (1, 2), (2, 3), (3, 0), (1, 3), (3, 10), (10, 11), (10, 12), (12, 13), (0, 14), (20, 21), (21, 22), (21, 23), (30, 31)]
    bg, links = blocked(graph(spark, pairs), parts=2), {}
    for r in bg.graph.edges.collect():
        links.setdefault(r["src"], []).append((r["dst"], r["w"]))
    folded, mass, left = apps.fold_pendants(bg.graph)
    assert {r["v"] for r in left.select(left["src"].alias("v")).collect()} == {0, 1, 2, 3} and folded.count() == 9
    assert {r["v"]: r["mass"] for r in mass.collect()} == {0: 2, 1: 1, 2: 1, 3: 5, 21: 4, 30: 2}
    got = {r["v"]: r["score"] for r in apps.betweenness_exact(bg, weighted, batch=3).collect()}
    want = _brandes(links, sorted(links), weighted)
    assert got.keys() == want.keys() and all(math.isclose(got[v], want[v], abs_tol=1e-6) for v in want)


def test_recursion_does_not_turn_back(spark):
    """From a leaf of a star over 1,500 leaves: a path a vertex, where turning back made 2.2 million."""
    g = graph(spark, [(0, i) for i in range(1, 1501)])
    got = {r["v"]: r["level"] for r in baselines.bfs_recursive(g, 7, 4).collect()}
    assert got == {v: 0 if v == 7 else 1 if v == 0 else 2 for v in range(1501)}


def test_inter_query_holds_flat_arrays(spark):
    """A worker's graph takes ten bytes an edge and twelve a vertex; lengths are those of the engine, in pieces and in any order."""
    bg = fx.build(spark, *fx.TWO_QUERIES)
    g, src = bg.graph, fx.sources(spark, "AI")
    whole = baselines._whole(g)
    assert sum(x.nbytes for x in whole.values()) <= 12 * g.links.count() + 12 * g.n_vertices + 4
    want = sorted(map(tuple, queries.multi_sssp(bg, src).collect()))
    for order in ("priority", "fifo", "lifo"):
        assert sorted(tuple(r)[:4] for r in baselines.inter_query_run(g, src, True, order=order, batch_rows=4).collect()) == want


def _host(bg):
    """All of a graph's parts in one task, and operations that start at its first and last vertex."""
    blocks = bg.blocks.toArrow()
    host = turns.ArrayHost(0, blocks.append_column("own", blocks["part_id"]))
    ops = {"q": np.arange(2), "v": host.ids[[0, -1]], "num": np.zeros(2), "aux": np.full(2, -1)}
    return host, ops, {c: np.empty(0, np.int64) for c in ("q", "v", "num", "aux", "rest")}


def test_a_task_gives_its_state_part_by_part(spark):
    """No task puts the state of its parts together before it is written: labels of many queries would not fit."""
    host, ops, none = _host(fx.build(spark, *fx.TWO_QUERIES))
    rows = lambda x: list(zip(*(x[c].tolist() for c in ("q", "v", "num", "aux")), strict=True))
    found = []
    left, _, _ = turns.on_arrays(Relax(True), Policy(), host, 2, ops, none, 2, 1.0, found.append)
    whole, _, _ = turns.on_arrays(Relax(True), Policy(), host, 2, ops, none, 2, 1.0)
    assert len(found) == 4 and not len(left["v"])
    assert sorted(r for x in found for r in rows(x)) == rows(whole) and len(whole["v"]) == 30


def test_operations_that_are_not_consolidated_run_on_arrays(spark):
    bg = fx.build(spark, *fx.TWO_QUERIES)

    class Arrays(Relax):
        def run(self, visit):
            raise AssertionError("run one by one")

    policy = policy_ladder(YieldPolicy(delta=2))["buffer"].but(turns=True)
    want = fx.lengths(fork(bg, fx.sources(spark, "AIO"), Relax(True)))
    assert fx.lengths(fork(bg, fx.sources(spark, "AIO"), Arrays(True), policy, traced=False)) == want


def test_arrival_order_holds_between_the_parts_of_a_task():
    """Rows of vertices, every fourth tied to the next row, cut across into parts: what a step makes is younger than what waits in another part, so a visit ends there and less is done twice."""
    n, dice = 64 * 64, random.Random(1)
    near = {(i, i + 1): dice.randint(1, 15) for i in range(n) if (i + 1) % 64} | {(i, i + 64): dice.randint(1, 15) for i in range(1, n - 64, 4)}
    out = [[] for _ in range(n)]
    for (a, b), w in near.items():
        out[a].append((b, w))
        out[b].append((a, w))
    rows = []
    for p in range(8):
        own = [v for v in range(n) if v % 64 // 8 == p]
        edges = [e for v in own for e in sorted(out[v])]
        offsets = np.cumsum([0, *(len(out[v]) for v in own)]).tolist()
        rows.append({"own": p, "part_id": 0, "vids": own, "offsets": offsets, "dst": [b for b, _ in edges], "dst_part": [b % 64 // 8 for b, _ in edges], "w": [w for _, w in edges]})
    host = turns.ArrayHost(0, pa.Table.from_pylist(rows))
    ops = {"q": np.arange(2), "v": host.ids[[0, -1]], "num": np.zeros(2), "aux": np.full(2, -1)}
    none = {c: np.empty(0, np.int64) for c in ("q", "v", "num", "aux", "rest")}
    heap, arrival = (turns.on_arrays(Relax(True), p, host, 2, ops, none, 2, 1.0) for p in (Policy(), Policy.fifo()))
    assert all((heap[0][c] == arrival[0][c]).all() for c in ("q", "v", "num", "aux"))
    assert arrival[2][2] < 1.8 * heap[2][2], (arrival[2], heap[2])


@pytest.mark.parametrize("weighted", [True, False])
def test_a_step_of_many_edges_is_followed_in_pieces(spark, monkeypatch, weighted):
    """A task never holds the edges of a whole frontier: they would be many times the block."""
    pairs = [(i, j) for i in range(40) for j in range(40, 60)]
    bg = blocked(graph(spark, pairs), parts=2)
    host, ops, none = _host(bg)
    whole = turns.on_arrays(Relax(weighted), Policy(), host, 2, ops, none, 2, 1.0)
    monkeypatch.setattr(vector, "STEP_EDGES", 50)
    seen, follow = [], vector.Lengths.follow
    monkeypatch.setattr(vector.Lengths, "follow", lambda self, now, u, degree: seen.append(int(degree.sum())) or follow(self, now, u, degree))
    pieces = turns.on_arrays(Relax(weighted), Policy(), host, 2, ops, none, 2, 1.0)
    assert all((whole[0][c] == pieces[0][c]).all() for c in ("q", "v", "num", "aux"))
    assert max(seen) < 50 + 40 and len(seen) > 10  # a piece may end with one vertex more


def test_a_task_counts_neighbours_in_other_parts():
    """Two vertices with 50 neighbours elsewhere take room for 52, so fewer queries run at a time."""
    row = {"own": 0, "part_id": 0, "vids": [0, 1], "offsets": [0, 50, 50], "dst": list(range(2, 52)), "dst_part": [1] * 50, "w": [1] * 50}
    assert turns.ArrayHost(0, pa.Table.from_pylist([row])).size == 52


def test_a_worker_gives_back_what_earlier_parts_took(monkeypatch):
    given = []

    class Pool:
        def release_unused(self):
            given.append(1)

    left = pa.Table.from_pylist([{"kind": "state", "query_id": 0, "seq": 0} | {c: [1] for c in engine.LISTS}])
    run = engine.make_kernel(Relax(True), Policy(), "t", 1, 1)
    monkeypatch.setattr(engine.pa, "default_memory_pool", Pool)
    run((pa.scalar(0), pa.scalar(0)), left, left)
    assert given


def test_edges_are_exchanged_once_to_their_chunks(spark):
    bg = fx.build(spark, *fx.TWO_QUERIES)
    plan = pack_blocks(bg.graph, bg.vparts)._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" not in plan and "Exchange hashpartitioning(src" not in plan and "Exchange hashpartitioning(dst" not in plan


def test_inter_query_levels_in_pieces(spark):
    bg = fx.build(spark, *fx.TWO_QUERIES)
    src = fx.sources(spark, "AI")
    want = sorted(map(tuple, queries.multi_bfs(bg, src).collect()))
    assert sorted(tuple(r)[:4] for r in baselines.inter_query_run(bg.graph, src, False, batch_rows=4).collect()) == want


def test_co_activity_pairs_stay_in_their_task(spark):
    """Pairs of users are counted where they are made: none of the plan's exchanges deals rows by dst, nor by pairs of events."""
    rows = [(m % 90, "ab"[m % 2], m % 7 if m % 11 else None) for m in range(200)]
    frame = spark.createDataFrame([(f"2024-01-01 0{m // 60}:{m % 60:02d}:00", t, u) for m, t, u in rows], "ts string, event_type string, user_id long").withColumn("ts", F.to_timestamp("ts"))
    found = requests.co_activity_counts(frame)
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "Exchange hashpartitioning(src" not in plan and "Exchange hashpartitioning(dst" not in plan
    want = {}
    for m, t, u in rows:
        for m2, t2, u2 in rows:
            if None not in (u, u2) and u != u2 and t == t2 and m // 60 == m2 // 60:
                want.setdefault((u, u2), []).append(m // 60)
    assert {(r["src"], r["dst"]): (r["windows"], r["n"]) for r in found.collect()} == {k: (len(set(v)), len(v)) for k, v in want.items()}


def test_decoded_blocks_are_flat():
    """A block of two chunks, out of order, in 20 bytes an edge."""
    rows = [{"vids": [5, 9], "offsets": [0, 2, 3], "dst": [1, 9, 5], "dst_part": [0, 0, 0], "w": [4, 2, 2]}, {"vids": [1, 7], "offsets": [0, 1, 1], "dst": [5], "dst_part": [0], "w": [4]}]
    kinds = {"vids": pa.int64(), "offsets": pa.int32(), "dst": pa.int64(), "dst_part": pa.int32(), "w": pa.int64()}
    block = LocalGraph(0, pa.table({c: pa.array([r[c] for r in rows], pa.list_(k)) for c, k in kinds.items()}))
    assert sum(len(x) * x.itemsize for x in (block.dst, block.dst_part, block.w)) == 20 * block.edges == 80
    assert {v: list(zip(block.dst[slice(*block.range[v])], block.w[slice(*block.range[v])], strict=True)) for v in (1, 5, 7, 9)} == {1: [(5, 4)], 5: [(1, 4), (9, 2)], 7: [], 9: [(5, 2)]}
    with pytest.raises(KeyError):
        block.range[6]


def test_large_parts_are_cut_to_fit_a_task(spark):
    """A plan of two parts, one with hubs: pieces stay within the bounds but for a single hub, lie in one part each, and give the same answers."""
    pairs = [(i, i + 1) for i in range(60)] + [(h, i) for h in (100, 101) for i in range(0, 40, 2)]
    g = settled(graph(spark, pairs))
    plan = partition.partition_chunk(g, 2)
    assert partition.cut_large(g, plan) is None
    cut = partition.cut_large(g, plan, most_edges=24, most_vertices=10).cache()
    degree = {r["id"]: r["deg"] for r in g.vertices.collect()}
    home, pieces = {r["id"]: r["part_id"] for r in plan.collect()}, {}
    for r in cut.collect():
        pieces.setdefault(r["part_id"], []).append(r["id"])
    assert sorted(v for own in pieces.values() for v in own) == sorted(degree)
    assert all(len({home[v] for v in own}) == 1 and len(own) <= 10 and (len(own) == 1 or sum(degree[v] for v in own) <= 24) for own in pieces.values())
    whole, fine = blocked(g, plan), blocked(g, plan)
    fine.__dict__["fitted"] = (cut, pack_blocks(g, cut))
    src = spark.createDataFrame([(0, 0), (1, 101)], "query_id int, src long")
    for make in (lambda b: queries.multi_bfs(b, src), lambda b: queries.multi_sssp(b, src), lambda b: queries.multi_walk(b, src, 6, 4)):
        assert sorted(map(tuple, make(fine).collect())) == sorted(map(tuple, make(whole).collect()))


@pytest.mark.parametrize(("query", "weighted"), [("bc_bfs_100", False), ("bc_sssp_100", True)])
def test_hundred_sources_against_brute_force(spark, query, weighted):
    sf = "/root/testdata/sf0.001"
    g, links = workloads.graph(spark, sf, "hyperlink"), {}
    for r in g.edges.collect():
        links.setdefault(r["src"], []).append((r["dst"], r["w"]))
    chosen = [r["src"] for r in seeds.sample_sources(g, 100).collect()]
    assert len(chosen) == 100
    want = _brandes(links, chosen, weighted)
    got = {r["v"]: r["score"] for r in workloads.queries()[query](spark, sf).collect()}
    assert got.keys() == want.keys() and all(math.isclose(got[v], want[v], abs_tol=0.01) for v in want)


def test_power_on_arrays_in_one_task_and_in_rounds(spark):
    pairs = [(1, 2), (2, 3), (3, 1), (3, 4), (4, 5), (11, 12), (12, 13), (13, 11), (21, 22)]
    for directed in (False, True):
        g = graph(spark, pairs, directed=directed)
        src = spark.createDataFrame([(0, 1), (1, 12), (2, 1)], "query_id int, src long")
        want = {(r["query_id"], r["v"]): r["p"] for r in baselines.ppr_power(g, src, rounds=9).collect()}
        for how in ({}, {"task_links": 3}, {"task_links": 3, "most_entries": 11}, {"most_entries": 5}):
            found = baselines.ppr_power_arrays(g, src, rounds=9, **how).collect()
            assert {(r["query_id"], r["v"]): r["p"] for r in found} == pytest.approx(want, abs=1e-12) and len(found) == len(want)
    with pytest.raises(ValueError):
        baselines.ppr_power_arrays(g, spark.createDataFrame([(0, 99)], "query_id int, src long"))


@pytest.mark.parametrize("most_sent", [1, 2_000_000])
def test_reached_part_is_closed_and_keeps_degrees_and_weights(spark, most_sent):
    g = graph(spark, [(1, 2), (2, 3), (3, 1), (3, 4), (11, 12), (12, 13), (21, 22)])
    part = reached(g, spark.createDataFrame([(0, 1), (1, 12)], "query_id int, src long"), most_sent)
    ids = {1, 2, 3, 4, 11, 12, 13}
    assert {r["id"]: r["deg"] for r in part.vertices.collect()} == {r["id"]: r["deg"] for r in g.vertices.collect() if r["id"] in ids}
    assert sorted(map(tuple, part.edges.collect())) == sorted(tuple(r) for r in g.edges.collect() if r["src"] in ids)
    assert part.n_vertices == 7 and blocked(part, parts=2).blocks.count() == 2
    ahead = reached(graph(spark, [(1, 2), (2, 3), (4, 1)], directed=True), spark.createDataFrame([(0, 2)], "query_id int, src long"), most_sent)
    assert sorted(r["id"] for r in ahead.vertices.collect()) == [2, 3]
    assert reached(g, spark.createDataFrame([(0, 1), (1, 12), (2, 22)], "query_id int, src long")) is g


def test_links_hold_every_pair_once_each_way(spark):
    pairs = [(1, 2), (2, 1), (1, 2), (3, 3), (None, 4), (5, None), (7, 6)]
    assert sorted(map(tuple, graph(spark, pairs).links.collect())) == [(1, 2), (2, 1), (6, 7), (7, 6)]


@pytest.mark.parametrize("weighted", [False, True])
def test_whole_graph_is_sorted_in_tasks(spark, weighted):
    g = graph(spark, [(1, 2), (2, 3), (3, 9), (9, 1), (4, 9), (5, 6)], directed=True)
    settled(g)
    want = {(r["src"], r["dst"]): r["w"] for r in g.edges.collect()}
    for part_edges in (1, 2, 100):
        held = baselines._whole(g, weighted, part_edges)
        owner = held["ids"][[v for v in range(len(held["ids"])) for _ in range(held["start"][v], held["start"][v + 1])]]
        found = list(zip(owner.tolist(), held["ids"][held["to"]].tolist(), strict=True))
        assert sorted(found) == sorted(want) and ("w" in held) == weighted
        assert not weighted or [want[x] for x in found] == held["w"].tolist()
