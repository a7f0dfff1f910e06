"""What may be tuned: order inside a query, order of parts, when a query pauses, how work is dealt."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace


@dataclass(frozen=True)
class YieldPolicy:
    """When a query stops in a part and leaves its other operations for later. A visit always runs one operation.

    edges: after this many times mu edges (mu: the part's edges by the number of queries).
    delta, factor: when the current value is worse than the visit's first by so much, or by this factor.
    floor: when the largest residual is below this.
    custom: (first value, current value, edges, operations) -> stop.
    """

    edges: float | None = None
    delta: float | None = None
    factor: float | None = None
    floor: float | None = None
    custom: Callable[[float, float, int, int], bool] | None = None

    @classmethod
    def none(cls) -> YieldPolicy:
        return cls()

    def stopper(self, mu: float, larger_first: bool) -> Callable[[float, float, int, int], bool] | None:
        """A test for one visit; None where the policy never stops."""
        tests: list[Callable[[float, float, int, int], bool]] = []
        if self.edges is not None:
            budget = self.edges * mu
            tests.append(lambda first, now, edges, ops: edges > budget)
        if self.delta is not None:
            tests.append((lambda first, now, edges, ops: now <= first - self.delta) if larger_first else (lambda first, now, edges, ops: now >= first + self.delta))
        if self.factor is not None:
            tests.append((lambda first, now, edges, ops: now * self.factor < first) if larger_first else (lambda first, now, edges, ops: now > self.factor * max(first, 1e-300)))
        if self.floor is not None:
            tests.append(lambda first, now, edges, ops: now < self.floor)
        if self.custom is not None:
            tests.append(self.custom)
        if not tests:
            return None
        return lambda first, now, edges, ops: any(t(first, now, edges, ops) for t in tests)


@dataclass(frozen=True)
class Pending:
    """What the driver knows of a part's buffer."""

    part_id: int
    best: float  # smaller is better
    oldest: int
    ops: int


Scheduler = Callable[[Pending, int], tuple]

SCHEDULERS: dict[str, Scheduler] = {
    "priority": lambda p, wave: (p.best, p.part_id),
    "fifo": lambda p, wave: (p.oldest, p.part_id),
    "max_ops": lambda p, wave: (-p.ops, p.part_id),
    "random": lambda p, wave: ((wave * 7919 + p.part_id * 104729 + 12345) * 48271 % 2147483647, p.part_id),
}


@dataclass(frozen=True)
class Policy:
    """order: 'priority', 'fifo' or 'lifo' inside a query. scheduler: a name or a key function. wave_width: parts per wave, None for all.

    alone: a batch of one query is run by the parallel frontier algorithm instead.
    turns: a task holds neighbouring parts and runs their visits by turns until none has operations left; waves are then of such
    groups, and wave_width and window hold for them.
    """

    order: str = "priority"
    scheduler: str | Scheduler = "priority"
    pause: YieldPolicy = field(default_factory=YieldPolicy)
    wave_width: int | None = None
    window: float | None = None
    buckets: int = 1
    consolidate: bool = True
    alone: bool = False
    turns: bool = False

    def choose(self, pending: list[Pending], wave: int) -> list[int]:
        """The parts of this wave: the first by the scheduler's key; with a window, those within it of the best."""
        key = SCHEDULERS[self.scheduler] if isinstance(self.scheduler, str) else self.scheduler
        ranked = sorted(pending, key=lambda p: key(p, wave))
        if self.window is not None and ranked:
            best = min(p.best for p in ranked)
            ranked = [p for p in ranked if p.best <= best + self.window]
        return [p.part_id for p in (ranked if self.wave_width is None else ranked[: self.wave_width])]

    def but(self, **changes) -> Policy:
        return replace(self, **changes)

    @classmethod
    def paths(cls, delta: float | None = None) -> Policy:
        return cls(pause=YieldPolicy(delta=delta))

    @classmethod
    def levels(cls, delta: float | None = None) -> Policy:
        return cls(pause=YieldPolicy(delta=delta))

    @classmethod
    def ppr(cls, mu_factor: float | None = 1.0) -> Policy:
        return cls(pause=YieldPolicy(edges=mu_factor))

    @classmethod
    def fifo(cls) -> Policy:
        return cls(order="fifo", scheduler="fifo")


def policy_ladder(pause: YieldPolicy, wave_width: int | None = None) -> dict[str, Policy]:
    """The engine's techniques, added one by one."""
    buffer = Policy(order="fifo", scheduler="fifo", consolidate=False, buckets=2, wave_width=wave_width)
    together = Policy(order="priority", scheduler="fifo", wave_width=wave_width)
    return {"buffer": buffer, "consolidation": together, "priority": together.but(scheduler="priority"), "yield": together.but(scheduler="priority", pause=pause)}
