"""Turns: a task holds several parts and runs their visits one after another, until none of them has operations left.

The order of visits is the policy's order of parts, queries pause as it says, and what a part sends to another of the same
task is in that one's buffer at once. Only operations for parts of other tasks wait for the next wave.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from typing import Any

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from manyq.plans import vector
from manyq.plans.kernels import Kernel, LocalGraph, Visit
from manyq.plans.policy import Pending, Policy

#: Edges and vertices that a task's parts have together at most, unless one part alone has more.
MOST_EDGES, MOST_VERTICES = 4_000_000, 500_000
#: Entries of (query, vertex) that a task gives back at most.
MOST_ENTRIES = 4_000_000
VALUES = ("num", "aux", "aux2", "rest")


class Host:
    """The parts of one task, decoded."""

    decode: Callable[[int, pa.Table], Any]

    def __init__(self, host: int, table: pa.Table):
        own = np.unique(table["own"].to_numpy())
        self.parts = {p: self.decode(p, table.filter(pc.equal(table["own"], p))) for p in own.tolist()}
        ids = {p: g.ids[: g.own] if isinstance(g, vector.ArrayGraph) else g.range.vids for p, g in self.parts.items()}
        place = np.concatenate([np.full(len(x), p) for p, x in ids.items()])
        ids = np.concatenate(list(ids.values()))
        order = np.argsort(ids)
        self.ids, self.place = ids[order], place[order]
        self.edges = sum(g.edges for g in self.parts.values())
        self.size = sum(g.size if isinstance(g, vector.ArrayGraph) else len(g.range.vids) for g in self.parts.values())  # with room for neighbours elsewhere

    def place_of(self, v: np.ndarray) -> np.ndarray:
        """The parts of vertices of this task."""
        return self.place[np.searchsorted(self.ids, v)]


class ArrayHost(Host):
    decode = vector.ArrayGraph


class LocalHost(Host):
    decode = LocalGraph


def hosts_of(blocks: DataFrame, most_edges: int | None = None, most_vertices: int | None = None) -> tuple[np.ndarray, int]:
    """(host of each part, vertices of the largest): neighbouring parts are together while a task can hold them."""
    most_edges, most_vertices = most_edges or MOST_EDGES, most_vertices or MOST_VERTICES
    sized = blocks.groupBy("part_id").agg(F.sum(F.size("dst")).alias("edges"), F.sum(F.size("vids")).alias("n")).orderBy("part_id").collect()  # a row per part
    out = np.zeros(max((r["part_id"] for r in sized), default=-1) + 1, np.int64)
    host, edges, n, largest = 0, 0, 0, 0
    for r in sized:
        if n and (edges + r["edges"] > most_edges or n + r["n"] > most_vertices):
            host, edges, n = host + 1, 0, 0
        edges, n = edges + r["edges"], n + r["n"]
        largest = max(largest, n)
        out[r["part_id"]] = host
    return out, largest


def shares(n: int, hosts: int, largest: int, policy: Policy) -> tuple[int, int]:
    """(batches of queries, tasks that share a batch at one host): a task's entries stay within bounds, and blocks are not sent to too many tasks."""
    at_once = max(1, MOST_ENTRIES // max(1, largest))
    most = max(8, math.ceil(64 / max(1, hosts)), policy.buckets)
    batches = max(1, math.ceil(n / (at_once * most)))
    each = math.ceil(n / batches)
    return batches, max(1, policy.buckets, min(each, max(math.ceil(each / at_once), math.ceil(8 / max(1, hosts)))))


class _Buffers:
    """What waits in a task, by part, and the policy's choice among it."""

    def __init__(self, policy: Policy):
        self.policy, self.turn, self.seq = policy, 0, 0
        self.held: dict[int, list] = {}
        self.pending: dict[int, Pending] = {}

    def put(self, part: int, best: float, n: int, ops: Any) -> None:
        p = self.pending.get(part)
        self.seq += 1
        self.pending[part] = Pending(part, best, self.seq, n) if p is None else Pending(part, min(p.best, best), p.oldest, p.ops + n)
        self.held.setdefault(part, []).append(ops)

    def take(self) -> tuple[int, list]:
        self.turn += 1
        part = next(iter(self.pending)) if len(self.pending) == 1 else self.policy.choose(list(self.pending.values()), self.turn)[0]
        del self.pending[part]
        return part, self.held.pop(part)


def _joined(pieces: list[dict[str, np.ndarray]], names: tuple[str, ...]) -> dict[str, np.ndarray]:
    """Rows of pieces in one; without any, empty columns."""
    kinds = {"num": np.float64, "rest": np.float64}
    return {c: np.concatenate([x[c] for x in pieces]) if pieces else np.empty(0, kinds.get(c, np.int64)) for c in names}


def _merged(sent: dict[str, np.ndarray], combine: str) -> dict[str, np.ndarray]:
    """What several visits sent to one (query, vertex), as one operation."""
    order = np.lexsort((sent["aux"], sent["num"], sent["v"], sent["q"]))
    sent = {c: x[order] for c, x in sent.items()}
    if combine == "none" or not len(order):
        return sent
    head = np.flatnonzero(np.append(True, (sent["q"][1:] != sent["q"][:-1]) | (sent["v"][1:] != sent["v"][:-1])))
    out = {c: x[head] for c, x in sent.items()}
    if combine == "sum":
        out["num"] = np.add.reduceat(sent["num"], head)
    return out


def on_arrays(kernel: Kernel, policy: Policy, host: ArrayHost, queries: int, ops: dict[str, np.ndarray], state: dict[str, np.ndarray], n_queries: int, factor: float, emit: Callable | None = None) -> tuple[dict, dict, tuple[int, int, int]]:
    """(changed state, operations for other hosts' parts, (done, pruned, edges)) of a slab of queries (q: 0..), all of a part's queries together.

    emit: is given the changed state part by part, in no order, and none is returned; a part's arrays are let go before the next one's.
    """
    buffers, cells, away = _Buffers(policy), {}, []
    ordered = policy.order == policy.scheduler == "priority"  # then parts of a task share one order
    by_age = policy.order == policy.scheduler == "fifo"  # so they do here: what a step makes is younger than what waits elsewhere
    by_part = {}
    if len(state["v"]):
        place = host.place_of(state["v"])
        by_part = {p: {c: x[place == p] for c, x in state.items()} for p in np.unique(place).tolist()}
    place = host.place_of(ops["v"])
    for p in np.unique(place).tolist():
        own = place == p
        buffers.put(p, float((factor * ops["num"][own]).min()), int(own.sum()), {c: ops[c][own] for c in ("q", "v", "num", "aux")})
    while buffers.pending:
        part, held = buffers.take()
        cell = cells.get(part)
        if cell is None:
            graph = host.parts[part]
            cell = cells[part] = kernel.cell(kernel, graph, queries, policy, graph.edges / max(1, n_queries))
            if part in by_part:
                cell.load(by_part.pop(part))
        held = [x for x in held if x is not None]
        others = min((p.best for p in buffers.pending.values()), default=math.inf) if ordered else math.inf
        cell.visit(held[0] if len(held) == 1 else _joined(held, ("q", "v", "num", "aux")), others, by_age and bool(buffers.pending))
        if len(cell.todo):
            buffers.put(part, cell.best(), len(cell.todo), None)
        sent = cell.sent()
        for to in np.unique(sent["to"]).tolist():
            own = sent["to"] == to
            x = {c: sent[c][own] for c in ("q", "to", "v", "num", "aux")}
            if to in host.parts:
                buffers.put(to, float((factor * x["num"]).min()), len(x["v"]), x)
            else:
                away.append(x)
    counts = tuple(sum(getattr(c, name) for c in cells.values()) for name in ("done", "pruned", "edges"))
    found = []
    cell = None
    while cells:
        (emit or found.append)(cells.popitem()[1].changed())
    changed = _joined(found, ("q", "v", "num", "aux", "rest"))
    found.clear()
    order = np.lexsort((changed["v"], changed["q"]))
    return {c: x[order] for c, x in changed.items()}, _merged(_joined(away, ("q", "to", "v", "num", "aux")), kernel.combine), counts


def one_by_one(kernel: Kernel, policy: Policy, host: LocalHost, ops: dict[str, np.ndarray], state: dict[str, np.ndarray], queries: np.ndarray, n_queries: int) -> tuple[dict, dict, tuple[int, int, int]]:
    """The same, query by query and operation by operation; q counts into queries."""
    number = {q: i for i, q in enumerate(queries.tolist())}
    buffers = _Buffers(policy)
    held: dict[tuple[int, int], dict] = {}
    for p, q, v, *s in zip(host.place_of(state["v"]).tolist(), *(state[c].tolist() for c in ("query_id", "v", *VALUES)), strict=True):
        if q in number:
            held.setdefault((p, q), {})[(v, s[2]) if kernel.keyed else v] = tuple(s)
    columns = [host.place_of(ops["v"]).tolist(), *(ops[c].tolist() for c in ("query_id", "seq", "v", "num", "aux", "aux2"))]
    for q, _, p, *op in sorted((q, seq, p, *op) for p, q, seq, *op in zip(*columns, strict=True)):
        buffers.put(p, kernel.priority(op), 1, (q, tuple(op)))
    changed: dict[tuple[int, int], set] = {}
    away: dict[tuple, tuple] = {}
    counts = [0, 0, 0]
    while buffers.pending:
        part, waiting = buffers.take()
        graph = host.parts[part]
        asked: dict[int, list] = {}
        for q, op in waiting:
            asked.setdefault(q, []).append(op)
        for q, own in asked.items():
            visit = Visit(q, graph, held.setdefault((part, q), {}), own, policy, graph.edges / max(1, n_queries))
            kernel.run(visit)
            counts = [a + b for a, b in zip(counts, (visit.done, visit.pruned, visit.edges), strict=True)]
            changed.setdefault((part, q), set()).update(visit.changed)
            for op in visit.keep:
                buffers.put(part, kernel.priority(op), 1, (q, op))
            for (to, v, *more), values in visit.send.items():
                if to in host.parts:
                    buffers.put(to, kernel.priority((v, *values)), 1, (q, (v, *values)))
                    continue
                key = (q, to, v, *more) if kernel.combine != "none" else (q, to, v, len(away))
                old = away.get(key)
                if kernel.combine == "sum" and old is not None:
                    values = (old[0] + values[0], old[1] + values[1], values[2])
                if old is None or kernel.combine == "sum" or values < old:
                    away[key] = values
    kinds = (np.int64, np.int64, np.float64, np.int64, np.int64, np.float64)
    rows = sorted((number[q], k[0] if isinstance(k, tuple) else k, *held[p, q][k]) for (p, q), own in changed.items() for k in own)
    found = {c: np.array(x, k) for c, x, k in zip(("q", "v", *VALUES), zip(*rows, strict=True) if rows else [[]] * 6, kinds, strict=True)}
    rows = [(number[key[0]], key[1], key[2], *values) for key, values in away.items()]
    sent = {c: np.array(x, k) for c, x, k in zip(("q", "to", "v", "num", "aux", "aux2"), zip(*rows, strict=True) if rows else [[]] * 6, (np.int64, *kinds[:5]), strict=True)}
    return found, sent, tuple(counts)
