"""Batch kernels: all queries that have operations in a part, run together on arrays.

Every step takes, for each query, its best open entries, and follows their edges in one go. A query's own order is kept,
so its work is that of a queue with buckets; what is shared is the cost of a step. State is two flat arrays over
(query, vertex), with room for the block's neighbours in other parts: what they collect is what will be sent.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from typing import TYPE_CHECKING

import numpy as np
import pyarrow as pa

from manyq.plans.policy import Policy

if TYPE_CHECKING:
    from manyq.plans.kernels import Push, Relax

#: Entries of (query, vertex) held at a time; a part's queries are run in slabs of so many.
SLAB = 4_500_000
#: Edges that a step follows at a time, unless one vertex alone has more.
STEP_EDGES = 250_000
NONE = np.iinfo(np.int64).max


class ArrayGraph:
    """A part's adjacency as arrays: vertices by local number, and after them the neighbours in other parts."""

    def __init__(self, part: int, table: pa.Table):
        vids, deg, dst, place, w = [], [], [], [], []
        for chunk in range(table.num_rows):
            row = {c: table[c][chunk].values.to_numpy(zero_copy_only=False) for c in ("vids", "offsets", "dst", "dst_part", "w")}
            vids.append(row["vids"])
            deg.append(np.diff(row["offsets"]))
            dst.append(row["dst"])
            place.append(row["dst_part"])
            w.append(row["w"])
        join = lambda x, kind: np.concatenate(x).astype(kind) if x else np.empty(0, kind)
        vids, deg, dst, place, self.w = join(vids, np.int64), join(deg, np.int64), join(dst, np.int64), join(place, np.int64), join(w, np.float64)
        starts = np.cumsum(deg) - deg
        order = np.argsort(vids)
        self.part, self.edges, self.own = part, len(dst), len(vids)
        self.start, self.degree = starts[order], deg[order]
        away = place != part
        ghosts, first = np.unique(dst[away], return_index=True)
        self.ids = np.concatenate([vids[order], ghosts])
        self.ghost_part = place[away][first]
        self.to = np.empty(len(dst), np.int32)
        self.to[~away] = np.searchsorted(self.ids[: self.own], dst[~away])
        self.to[away] = self.own + np.searchsorted(ghosts, dst[away])
        self.size = len(self.ids)
        self.step = float(self.w.mean()) if len(self.w) else 1.0

    def local(self, v: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.ids[: self.own], v)

    def out(self, u: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(which of u, edge) for all out-edges of vertices u."""
        n = self.degree[u]
        which = np.repeat(np.arange(len(u)), n)
        return which, np.arange(len(which)) + np.repeat(self.start[u] - (np.cumsum(n) - n), n)


@dataclass
class Batch:
    """One slab of a part's visit: rows of operations and state by query number (0..), and what comes of them."""

    graph: ArrayGraph
    queries: np.ndarray
    ops: dict[str, np.ndarray]  # q, v, num, aux
    state: dict[str, np.ndarray]  # q, v, num, aux, rest; later rows replace earlier ones
    policy: Policy
    mu: float
    changed: dict[str, np.ndarray] = field(default_factory=dict)  # q, v, num, aux, rest
    keep: dict[str, np.ndarray] = field(default_factory=dict)  # q, v, num, aux
    send: dict[str, np.ndarray] = field(default_factory=dict)  # q, to, v, num, aux
    edges: int = 0
    pruned: int = 0
    done: int = 0


class _Pauses:
    """Which queries have stopped in this visit."""

    def __init__(self, policy: Policy, mu: float, n: int, larger_first: bool):
        self.test = policy.pause.stopper(mu, larger_first)
        self.first = np.full(n, np.nan)
        self.edges, self.done, self.stopped = np.zeros(n), np.zeros(n, np.int64), np.zeros(n, bool)

    def ask(self, now: np.ndarray, open_: np.ndarray) -> None:
        """now: every query's best value; open_: whether it has any."""
        fresh = open_ & np.isnan(self.first)
        self.first[fresh] = now[fresh]
        if self.test is not None:
            for q in np.flatnonzero(open_ & ~fresh & ~self.stopped):
                self.stopped[q] = self.test(float(self.first[q]), float(now[q]), int(self.edges[q]), int(self.done[q]))

    def count(self, q: np.ndarray, edges: np.ndarray) -> None:
        n = len(self.done)
        self.edges += np.bincount(q, edges, n)
        self.done += np.bincount(q, minlength=n)


class Lengths:
    """Shortest lengths of a slab of queries in one part, kept between its visits. The open entries within a mean weight of their query's best one are followed together, as in a queue of buckets."""

    def __init__(self, kernel: Relax, graph: ArrayGraph, n: int, policy: Policy, mu: float):
        self.kernel, self.graph, self.n, self.policy, self.mu = kernel, graph, n, policy, mu
        self.dist = np.full(n * graph.size, np.inf)
        self.pred = np.full(n * graph.size, NONE)
        self.open, self.touched = np.zeros(n * graph.size, bool), np.zeros(n * graph.size, bool)
        self.mark = np.empty(n * graph.size, np.int32)
        self.todo = np.empty(0, np.int64)
        self.away: list[np.ndarray] = []  # neighbours in other parts that improved and were not told yet
        self.edges = self.pruned = self.done = 0

    def load(self, state: dict[str, np.ndarray]) -> None:
        """Rows q, v, num, aux, rest; later rows replace earlier ones."""
        at = state["q"] * self.graph.size + self.graph.local(state["v"])
        self.dist[at], self.pred[at] = state["num"], state["aux"]
        self.open[at] = state["rest"] > 0  # left open by an earlier visit
        self.touched |= self.open
        self.todo = np.flatnonzero(self.open)

    def improve(self, f: np.ndarray, at: np.ndarray, num: np.ndarray, aux: np.ndarray) -> np.ndarray:
        """Own places whose length fell and that were not open, once each; they are open now. at: the local numbers of places f."""
        old = self.dist[f]
        good = np.flatnonzero(num <= old)
        f, at, num, aux, old = f[good], at[good], num[good], aux[good], old[good]
        same = num == old
        if same.any():  # an equal length counts only by a lesser predecessor
            good = np.flatnonzero(~same | (aux < self.pred[f]))
            f, at, num, aux, old = f[good], at[good], num[good], aux[good], old[good]
        np.minimum.at(self.dist, f, num)
        least = num == self.dist[f]
        if not least.all():
            f, at, num, aux, old = f[least], at[least], num[least], aux[least], old[least]
        fell = num < old
        self.pred[f[fell]] = NONE
        np.minimum.at(self.pred, f, aux)
        self.touched[f] = True
        if self.graph.size > self.graph.own:
            out = at >= self.graph.own
            if out.any():
                self.away.append(f[out])
                fell &= ~out
        fresh = f[fell & ~self.open[f]]
        self.open[fresh] = True
        number = np.arange(len(fresh), dtype=np.int32)
        self.mark[fresh] = number
        return fresh[self.mark[fresh] == number]

    def follow(self, now: np.ndarray, u: np.ndarray, degree: np.ndarray) -> np.ndarray:
        """The edges of places now, of vertices u: places that are to be followed next."""
        g, kernel = self.graph, self.kernel
        ends = np.cumsum(degree)
        edge = np.arange(ends[-1]) + np.repeat(g.start[u] - (ends - degree), degree)
        at, num = g.to[edge], np.repeat(self.dist[now], degree)
        num += g.w[edge] if kernel.weighted else 1.0
        f, aux = np.repeat(now - u, degree) + at, np.repeat(g.ids[u], degree)
        if kernel.cutoff is not None:
            near = num <= kernel.cutoff
            f, at, num, aux = f[near], at[near], num[near], aux[near]
        return self.improve(f, at, num, aux)

    def visit(self, ops: dict[str, np.ndarray], bound: float = np.inf, brief: bool = False) -> None:
        """Rows q, v, num, aux; until nothing is open or every query has paused. After its first step a query also stops beyond bound, the best that another part waits with, and three buckets more. brief: one step only."""
        g, n = self.graph, self.n
        at = g.local(ops["v"])
        was = len(ops["q"])
        fresh = self.improve(ops["q"] * g.size + at, at, ops["num"], ops["aux"])
        self.pruned += was - len(fresh)
        todo = np.concatenate([self.todo, fresh])
        pauses = _Pauses(self.policy, self.mu, n, False)
        width = g.step if self.kernel.weighted else 1.0
        ordered = self.policy.order == "priority"
        bound, begun = bound + 3 * width, False
        while len(todo) and not (begun and brief):
            now = todo
            if ordered or pauses.test is not None or bound < np.inf:
                q, d = (todo // g.size if n > 1 else np.zeros(len(todo), np.int64)), self.dist[todo]
                best = np.full(n, np.inf)
                np.minimum.at(best, q, d)
                most = best + width if ordered else np.full(n, np.inf)
                if pauses.test is not None:
                    pauses.ask(best, best < np.inf)
                    most[pauses.stopped] = -np.inf
                if begun and bound < np.inf:
                    most[best > bound] = -np.inf
                take = d < most[q]
                now = todo[take]
                if not len(now):
                    break
            begun = True
            u = now % g.size if n > 1 else now
            self.open[now] = False
            degree = g.degree[u]
            edges = int(degree.sum())
            self.edges, self.done = self.edges + edges, self.done + len(now)
            if pauses.test is not None:
                pauses.count(q[take], degree)
            left = [] if now is todo else [todo[~take]]
            if edges <= STEP_EDGES:
                left.append(self.follow(now, u, degree) if edges else now[:0])
            else:
                cuts = np.flatnonzero(np.diff(np.cumsum(degree) // STEP_EDGES)) + 1
                for piece in np.split(np.arange(len(now)), cuts):
                    if degree[piece].any():
                        left.append(self.follow(now[piece], u[piece], degree[piece]))
            todo = left[0] if len(left) == 1 else np.concatenate(left)
        self.todo = todo

    def named(self, f: np.ndarray) -> dict[str, np.ndarray]:
        return {"q": f // self.graph.size, "v": self.graph.ids[f % self.graph.size], "num": self.dist[f], "aux": self.pred[f]}

    def best(self) -> float:
        """The best priority of what is open."""
        return float(self.dist[self.todo].min())

    def changed(self) -> dict[str, np.ndarray]:
        f = np.flatnonzero(self.touched)
        f = f[f % self.graph.size < self.graph.own]
        return self.named(f) | {"rest": self.open[f].astype(float)}

    def kept(self) -> dict[str, np.ndarray]:
        return self.named(np.sort(self.todo))

    def sent(self) -> dict[str, np.ndarray]:
        """What other parts are to be told; asked once a visit."""
        f = np.unique(np.concatenate(self.away)) if self.away else np.empty(0, np.int64)
        self.away = []
        return self.named(f) | {"to": self.graph.ghost_part[f % self.graph.size - self.graph.own]}


class Ranks:
    """Residuals of a slab of queries in one part, kept between its visits. Every step pushes the open vertices whose residual is at least half of their query's largest, or all in arrival order."""

    def __init__(self, kernel: Push, graph: ArrayGraph, n: int, policy: Policy, mu: float):
        self.kernel, self.graph, self.n, self.policy, self.mu = kernel, graph, n, policy, mu
        self.rank, self.rest = np.zeros(n * graph.size), np.zeros(n * graph.size)
        self.open, self.seen = np.zeros(n * graph.size, bool), np.zeros(n * graph.size, bool)
        self.bar = np.concatenate([kernel.eps * graph.degree, np.full(graph.size - graph.own, np.inf)])
        self.todo = np.empty(0, np.int64)
        self.edges = self.pruned = self.done = 0

    def load(self, state: dict[str, np.ndarray]) -> None:
        at = state["q"] * self.graph.size + self.graph.local(state["v"])
        self.rank[at], self.rest[at] = state["num"], state["rest"]

    def visit(self, ops: dict[str, np.ndarray], bound: float = np.inf, brief: bool = False) -> None:
        g, n, kernel, rank, rest, open_ = self.graph, self.n, self.kernel, self.rank, self.rest, self.open
        f = ops["q"] * g.size + g.local(ops["v"])
        order = np.lexsort((ops["num"], f))
        np.add.at(rest, f[order], ops["num"][order])
        self.seen[f] = True
        fresh = np.unique(f)
        fresh = fresh[(rest[fresh] >= self.bar[fresh % g.size]) & (rest[fresh] > 0) & ~open_[fresh]]
        open_[fresh] = True
        todo = np.concatenate([self.todo, fresh])
        pauses = _Pauses(self.policy, self.mu, n, True)
        while len(todo):
            q, r = todo // g.size, rest[todo]
            best = np.zeros(n)
            np.maximum.at(best, q, r)
            take = r >= best[q] / 2 if self.policy.order == "priority" else np.ones(len(todo), bool)
            if pauses.test is not None:
                pauses.ask(best, best > 0)
                take &= ~pauses.stopped[q]
                if not take.any():
                    break
            now, r = todo[take], r[take]
            u = now % g.size
            open_[now] = False
            deg = g.degree[u]
            pauses.count(q[take], deg)
            sink = deg == 0
            rank[now] += np.where(sink, r, kernel.alpha * r)
            moves = (1 - kernel.alpha) * r
            rest[now] = np.where(sink, 0.0, moves / 2 if kernel.lazy else 0.0)
            which, edge = g.out(u)
            share = ((moves / 2 if kernel.lazy else moves) / np.maximum(deg, 1))[which]
            f = (now - u)[which] + g.to[edge]
            np.add.at(rest, f, share)
            self.seen[f] = True
            f = np.concatenate([f, now]) if kernel.lazy else f
            hot = f[(rest[f] >= self.bar[f % g.size]) & ~open_[f]]
            hot = np.unique(hot)
            hot = hot[rest[hot] > 0]
            open_[hot] = True
            todo = np.concatenate([todo[~take], hot])
            if brief:
                break
        self.todo = todo
        self.edges += int(pauses.edges.sum())
        self.done += int(pauses.done.sum())

    def named(self, f: np.ndarray) -> dict[str, np.ndarray]:
        return {"q": f // self.graph.size, "v": self.graph.ids[f % self.graph.size]}

    def best(self) -> float:
        return -float(self.rest[self.todo].max())

    def changed(self) -> dict[str, np.ndarray]:
        f = np.flatnonzero(self.seen)
        f = f[f % self.graph.size < self.graph.own]
        return self.named(f) | {"num": self.rank[f], "aux": np.zeros(len(f), np.int64), "rest": self.rest[f]}

    def kept(self) -> dict[str, np.ndarray]:
        """What is paused keeps its residual in the state; a zero operation brings it back."""
        f = np.sort(self.todo)
        return self.named(f) | {"num": np.zeros(len(f)), "aux": np.full(len(f), -1)}

    def sent(self) -> dict[str, np.ndarray]:
        f = np.flatnonzero(self.seen)
        f = f[f % self.graph.size >= self.graph.own]
        out = self.named(f) | {"to": self.graph.ghost_part[f % self.graph.size - self.graph.own], "num": self.rest[f], "aux": np.full(len(f), -1)}
        self.seen[f], self.rest[f] = False, 0.0
        return out


def _visit(cell: Lengths | Ranks, b: Batch) -> None:
    """One visit alone: state in, operations in, all three out."""
    cell.load(b.state)
    cell.visit(b.ops)
    b.edges, b.pruned, b.done = cell.edges, cell.pruned, cell.done
    b.changed, b.keep, b.send = cell.changed(), cell.kept(), cell.sent()


def relax(kernel: Relax, b: Batch) -> None:
    _visit(Lengths(kernel, b.graph, len(b.queries), b.policy, b.mu), b)


def push(kernel: Push, b: Batch) -> None:
    _visit(Ranks(kernel, b.graph, len(b.queries), b.policy, b.mu), b)
