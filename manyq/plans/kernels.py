"""Sequential kernels: what one query does with its operations in one part. Plain Python on decoded blocks.

An operation is (v, num, aux, aux2); state maps a vertex to (num, aux, aux2, rest). A kernel changes the state it is
given and reports changed vertices, operations kept for a later visit, and operations for other parts, combined.
"""

from __future__ import annotations

import heapq
from array import array
from collections import deque
from collections.abc import Callable
from dataclasses import dataclass, field
from typing import Any

import numpy as np
import pyarrow as pa

from manyq.functions.ids import step_choice
from manyq.plans import vector
from manyq.plans.policy import Policy
from manyq.plans.vector import Batch

Op = tuple[int, float, int, int]


class _Ranges:
    """v -> (a, b) from sorted vertices and where their edges begin."""

    def __init__(self, vids: np.ndarray, start: np.ndarray, degree: np.ndarray):
        self.vids, self.start, self.degree = vids, start, degree

    def __getitem__(self, v: int) -> tuple[int, int]:
        i = int(self.vids.searchsorted(v))
        if i == len(self.vids) or self.vids[i] != v:
            raise KeyError(v)
        a = int(self.start[i])
        return a, a + int(self.degree[i])


class LocalGraph:
    """A part's adjacency: range[v] gives the range of v's edges in dst, dst_part, w; flat arrays, some 20 bytes an edge."""

    def __init__(self, part: int, table: pa.Table):
        self.part = part
        self.dst, self.dst_part, self.w = array("q"), array("i"), array("q")
        vids, start, degree = [np.empty(0, np.int64)], [np.empty(0, np.int64)], [np.empty(0, np.int64)]
        for chunk in range(table.num_rows):
            row = {c: table[c][chunk].values.to_numpy(zero_copy_only=False) for c in ("vids", "offsets", "dst", "dst_part", "w")}
            vids.append(row["vids"])
            start.append(row["offsets"][:-1].astype(np.int64) + len(self.dst))
            degree.append(np.diff(row["offsets"]))
            for to, c in ((self.dst, "dst"), (self.dst_part, "dst_part"), (self.w, "w")):
                to.frombytes(np.ascontiguousarray(row[c], to.typecode).data.cast("B"))
        vids, start, degree = (np.concatenate(x) for x in (vids, start, degree))
        order = np.argsort(vids)
        self.range = _Ranges(vids[order], start[order], degree[order])
        self.edges = len(self.dst)


class QueryDag:
    """Edges by query: what Countdown runs on."""

    def __init__(self, part: int, table: pa.Table):
        self.part, self.edges = part, table.num_rows
        self.out: dict[tuple[int, int], list[tuple[int, int]]] = {}
        for q, u, v, p in zip(*(table[c].to_pylist() for c in ("query_id", "u", "v", "v_part")), strict=True):
            self.out.setdefault((q, u), []).append((v, p))


@dataclass
class Visit:
    """What one query does in one part in one wave."""

    query: int
    graph: Any
    state: dict[int, tuple]
    ops: list[Op]
    policy: Policy
    mu: float
    changed: set[int] = field(default_factory=set)
    keep: list[Op] = field(default_factory=list)
    send: dict[tuple, tuple] = field(default_factory=dict)  # (part, v, ...) -> (num, aux, aux2)
    edges: int = 0
    pruned: int = 0
    done: int = 0


class Kernel:
    """combine: how operations of one query on one vertex merge: 'min' (of num, then aux), 'sum', or 'none'."""

    combine = "min"
    larger_first = False
    #: State rows are results only and need not come back.
    append_only = False
    #: A vertex has several state rows, told apart by aux2.
    keyed = False
    sides = LocalGraph
    #: Runs all queries of a part together on arrays, where the policy has one task per query and part.
    batch: Callable[[Any, Batch], None] | None = None
    #: The arrays of such a run, where a task keeps them between the visits of a part.
    cell: Any = None

    def priority(self, op: Op) -> float:
        """Smaller is better; of operations in a buffer, for the order of parts."""
        return op[1]

    def start(self, query: int, v: int) -> Op:
        return (v, 0.0, -1, 0)

    def run(self, visit: Visit) -> None:
        raise NotImplementedError


class Relax(Kernel):
    """Shortest lengths: levels where edges count one, else sums of weights. aux: the least predecessor of a shortest way."""

    batch = staticmethod(vector.relax)
    cell = vector.Lengths

    def __init__(self, weighted: bool, cutoff: float | None = None):
        self.weighted, self.cutoff = weighted, cutoff

    def run(self, visit: Visit) -> None:
        state, graph, order = visit.state, visit.graph, visit.policy.order
        stop = visit.policy.pause.stopper(visit.mu, False)
        queue: Any
        if order == "priority":
            queue = [(num, aux, v) for v, num, aux, _ in visit.ops]
            heapq.heapify(queue)
            take, put = heapq.heappop, heapq.heappush
        else:
            queue = deque((num, aux, v) for v, num, aux, _ in visit.ops)
            take, put = (deque.popleft if order == "fifo" else deque.pop), deque.append
        first = None
        limit = float("inf") if self.cutoff is None else self.cutoff
        while queue:
            num, aux, v = item = take(queue)
            if first is None:
                first = num
            elif stop is not None and stop(first, num, visit.edges, visit.done):
                put(queue, item)
                break
            old = state.get(v)
            if old is not None and (old[0] < num or old[0] == num and old[1] <= aux):
                visit.pruned += 1
                continue
            visit.done += 1
            state[v] = (num, aux, 0, 0.0)
            visit.changed.add(v)
            if old is not None and old[0] == num:
                continue  # a smaller predecessor of the same length changes nothing further on
            a, b = graph.range[v]
            visit.edges += b - a
            for i in range(a, b):
                to = num + (graph.w[i] if self.weighted else 1)
                if to > limit:
                    continue
                u = graph.dst[i]
                if graph.dst_part[i] == graph.part:
                    known = state.get(u)
                    if known is None or to < known[0] or to == known[0] and v < known[1]:
                        put(queue, (to, v, u))
                else:
                    key = (graph.dst_part[i], u)
                    sent = visit.send.get(key)
                    if sent is None or (to, v) < sent[:2]:
                        visit.send[key] = (to, v, 0)
        visit.keep += [(v, num, aux, 0) for num, aux, v in queue]


class Push(Kernel):
    """Personalised PageRank by pushing residuals. State: num is the estimate, rest the residual; an operation adds residual.

    A vertex is pushed while its residual is at least eps times its degree. lazy: half of what is not kept stays. A vertex
    without out-edges keeps all its mass.
    """

    combine = "sum"
    larger_first = True
    batch = staticmethod(vector.push)
    cell = vector.Ranks

    def __init__(self, alpha: float = 0.15, eps: float = 1e-5, lazy: bool = False):
        self.alpha, self.eps, self.lazy = alpha, eps, lazy

    def priority(self, op: Op) -> float:
        return -op[1]

    def start(self, query: int, v: int) -> Op:
        return (v, 1.0, -1, 0)

    def run(self, visit: Visit) -> None:
        graph, eps, alpha = visit.graph, self.eps, self.alpha
        stop = visit.policy.pause.stopper(visit.mu, True)
        p = {v: s[0] for v, s in visit.state.items()}
        r = {v: s[3] for v, s in visit.state.items()}
        for v, num, _, _ in sorted(visit.ops):
            r[v] = r.get(v, 0.0) + num
            visit.changed.add(v)
        degree = {v: graph.range[v][1] - graph.range[v][0] for v in visit.changed}
        hot = [v for v in sorted(visit.changed) if r[v] >= eps * degree[v] and r[v] > 0]
        queue: Any = deque(hot) if visit.policy.order != "priority" else [(-r[v], v) for v in hot]
        heap = visit.policy.order == "priority"
        if heap:
            heapq.heapify(queue)
        waiting, first = set(hot), None
        while queue:
            v = heapq.heappop(queue)[1] if heap else queue.popleft()
            if v not in waiting:
                continue
            a, b = graph.range[v]
            res = r[v]
            if first is None:
                first = res
            elif stop is not None and stop(first, res, visit.edges, visit.done):
                break
            waiting.discard(v)
            visit.done += 1
            visit.changed.add(v)
            if a == b:
                p[v], r[v] = p.get(v, 0.0) + res, 0.0
                continue
            p[v] = p.get(v, 0.0) + alpha * res
            rest = (1 - alpha) * res
            r[v] = rest / 2 if self.lazy else 0.0
            share = (rest / 2 if self.lazy else rest) / (b - a)
            visit.edges += b - a
            touched = [v] if self.lazy else []
            for i in range(a, b):
                u = graph.dst[i]
                if graph.dst_part[i] == graph.part:
                    r[u] = r.get(u, 0.0) + share
                    touched.append(u)
                else:
                    key = (graph.dst_part[i], u)
                    sent = visit.send.get(key)
                    visit.send[key] = (share if sent is None else sent[0] + share, -1, 0)
            for u in touched:
                visit.changed.add(u)
                c, d = graph.range[u]
                if r[u] >= eps * (d - c) and u not in waiting:
                    waiting.add(u)
                    if heap:
                        heapq.heappush(queue, (-r[u], u))
                    else:
                        queue.append(u)
        # What is paused keeps its residual in the state; a zero operation brings it back.
        visit.keep += [(v, 0.0, -1, 0) for v in sorted(waiting)]
        for v in visit.changed:
            visit.state[v] = (p.get(v, 0.0), 0, 0, r.get(v, 0.0))


class Token(Kernel):
    """Depth-first search, neighbours in id order. One token per query walks the graph, across parts as well.

    An operation is the token: at v, num the next preorder number; aux the vertex it comes from, aux2 the depth (>= 0: going
    down; -1: coming back). State: num preorder, aux parent, aux2 depth, rest the next edge to try.
    """

    combine = "none"

    def run(self, visit: Visit) -> None:
        graph, state = visit.graph, visit.state
        stop = visit.policy.pause.stopper(visit.mu, False)
        for v, num, origin, depth in visit.ops:
            first = None
            while True:
                if first is None:
                    first = num
                elif stop is not None and stop(first, num, visit.edges, visit.done):
                    visit.keep.append((v, num, origin, depth))
                    break
                visit.done += 1
                if depth >= 0:
                    if v in state:
                        to, message = origin, (num, v, -1)
                        place = self._place_of(graph, v, origin)
                        visit.pruned += 1
                    else:
                        state[v] = (num, origin, depth, 0.0)
                        visit.changed.add(v)
                        num += 1
                        depth = -1
                        continue
                else:
                    pre, parent, own_depth, cursor = state[v]
                    a, b = graph.range[v]
                    i = a + int(cursor)
                    if i < b:
                        visit.edges += 1
                        state[v] = (pre, parent, own_depth, cursor + 1)
                        visit.changed.add(v)
                        to, message, place = graph.dst[i], (num, v, own_depth + 1), graph.dst_part[i]
                    elif parent < 0:
                        break
                    else:
                        to, message = parent, (num, v, -1)
                        place = self._place_of(graph, v, parent)
                if place == graph.part:
                    v, (num, origin, depth) = to, message
                else:
                    visit.send[(place, to)] = message
                    break

    @staticmethod
    def _place_of(graph: LocalGraph, v: int, u: int) -> int:
        """The part of a neighbour; ways back need the edge both ways."""
        a, b = graph.range[v]
        for i in range(a, b):
            if graph.dst[i] == u:
                return graph.dst_part[i]
        raise ValueError("depth-first search needs both directions of every edge")

    def start(self, query: int, v: int) -> Op:
        return (v, 0.0, -1, 0)


class Walk(Kernel):
    """Random walks. An operation: walk aux stands at v after aux2 steps. State rows are the visits, (walk, step) in aux and aux2.

    bias: 'uniform', or 'weight' for steps in proportion to weights. restart: the chance, in parts of 1000, to go home; num holds
    the source, and the bits of aux above the 32nd the source's part.
    """

    combine = "none"
    append_only = keyed = True

    def __init__(self, length: int, walks: int, restart: float = 0.0, bias: str = "uniform", seed: int = 0):
        self.length, self.walks, self.restart, self.bias, self.seed = length, walks, int(round(1000 * restart)), bias, seed

    def priority(self, op: Op) -> float:
        return float(op[3])

    def run(self, visit: Visit) -> None:
        graph = visit.graph
        for v, home, token, step in visit.ops:
            walk = token & 0xFFFFFFFF
            while True:
                visit.done += 1
                visit.state[v, walk, step] = (home, walk, step, 0.0)
                visit.changed.add((v, walk, step))
                if step == self.length:
                    break
                step += 1
                if self.restart and step_choice(visit.query, walk, step, 1000, self.seed + 1) < self.restart and v != int(home):
                    if token >> 32 == graph.part:
                        v = int(home)
                        continue
                    visit.send[(token >> 32, int(home), walk)] = (home, token, step)
                    break
                a, b = graph.range[v]
                if a == b:
                    break
                visit.edges += 1
                if self.bias == "uniform":
                    i = a + step_choice(visit.query, walk, step, b - a, self.seed)
                else:
                    sums = np.cumsum(graph.w[a:b])
                    i = a + int(np.searchsorted(sums, step_choice(visit.query, walk, step, int(sums[-1]), self.seed), "right"))
                u, place = graph.dst[i], graph.dst_part[i]
                if place != graph.part:
                    visit.send[(place, u, walk)] = (home, token, step)
                    break
                v = u


class KShortest(Kernel):
    """The k shortest lengths of walks from the source, as multisets. State keys are (v, rank); aux2 is the rank."""

    combine = "none"
    keyed = True

    def __init__(self, k: int, weighted: bool = True):
        self.k, self.weighted = k, weighted

    def run(self, visit: Visit) -> None:
        graph = visit.graph
        best: dict[int, list[float]] = {}
        for (v, _), s in sorted(visit.state.items()):
            best.setdefault(v, []).append(s[0])
        queue = [(num, v) for v, num, _, _ in visit.ops]
        heapq.heapify(queue)
        touched = set()
        while queue:
            num, v = heapq.heappop(queue)
            own = best.setdefault(v, [])
            if len(own) == self.k and num >= own[-1]:
                visit.pruned += 1
                continue
            visit.done += 1
            own.append(num)
            own.sort()
            del own[self.k :]
            touched.add(v)
            a, b = graph.range[v]
            visit.edges += b - a
            for i in range(a, b):
                to = num + (graph.w[i] if self.weighted else 1)
                if graph.dst_part[i] == graph.part:
                    heapq.heappush(queue, (to, graph.dst[i]))
                else:
                    visit.send[(graph.dst_part[i], graph.dst[i], len(visit.send))] = (to, -1, 0)
        for v in touched:
            for rank, num in enumerate(best[v]):
                visit.state[v, rank] = (num, 0, rank, 0.0)
                visit.changed.add((v, rank))


class Countdown(Kernel):
    """Sums along a query's own acyclic edges: a vertex fires once all its predecessors have.

    State: num the sum so far, aux predecessors still awaited, aux2 whether it fired, rest a factor. forward: a fired vertex
    passes its sum on. backward: it passes (1 + factor * sum) / factor, and factor * sum is its result.
    """

    combine = "sum"
    sides = QueryDag

    def __init__(self, backward: bool = False):
        self.backward = backward

    def run(self, visit: Visit) -> None:
        state, graph = visit.state, visit.graph
        ready = deque()
        for v, num, count, _ in sorted(visit.ops):
            total, left, fired, factor = state[v]
            state[v] = (total + num, left - count, fired, factor)
            visit.changed.add(v)
            if left - count == 0 and not fired:
                ready.append(v)
        while ready:
            v = ready.popleft()
            total, left, _, factor = state[v]
            state[v] = (total, left, 1, factor)
            visit.done += 1
            give = (1 + factor * total) / factor if self.backward else total
            for u, place in graph.out.get((visit.query, v), ()):
                visit.edges += 1
                if place == graph.part:
                    t, n, fired, f = state[u]
                    state[u] = (t + give, n - 1, fired, f)
                    visit.changed.add(u)
                    if n == 1:
                        ready.append(u)
                else:
                    sent = visit.send.get((place, u), (0.0, 0, 0))
                    visit.send[(place, u)] = (sent[0] + give, sent[1] + 1, 0)
