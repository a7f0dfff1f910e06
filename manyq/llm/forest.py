"""A forest of random-projection trees and its search through one shared priority queue; plain numpy, no Spark."""

from __future__ import annotations

import heapq
from dataclasses import dataclass

import numpy as np


@dataclass
class Tree:
    """Inner node i splits at normals[i] . x > offsets[i] into children[i] = (no, yes); a negative child c is leaf -c - 1."""

    normals: np.ndarray
    offsets: np.ndarray
    children: np.ndarray
    leaves: int

    def leaf_of(self, x: np.ndarray) -> np.ndarray:
        out = np.zeros(len(x), np.int64)
        if not len(self.normals):
            return out
        todo = [(0, np.arange(len(x)))]
        while todo:
            node, rows = todo.pop()
            yes = x[rows] @ self.normals[node] > self.offsets[node]
            for child, own in zip(self.children[node].tolist(), (rows[~yes], rows[yes]), strict=True):
                if child < 0:
                    out[own] = -child - 1
                elif len(own):
                    todo.append((child, own))
        return out


def grow(sample: np.ndarray, leaf_rows: int, rng: np.random.Generator) -> Tree:
    """Split by the direction between two random rows, at the median, until at most leaf_rows of the sample are together.

    Rows that no direction splits (copies of one vector) stay together, however many they are.
    """
    normals, offsets, children, leaves = [], [], [], 0

    def build(rows: np.ndarray) -> int:
        nonlocal leaves
        if len(rows) > leaf_rows:
            for _ in range(8):
                a, b = sample[rng.choice(rows, 2, replace=False)]
                length = np.linalg.norm(a - b)
                if length < 1e-9:
                    continue
                normal = (a - b) / length
                side = sample[rows] @ normal
                cut = float(np.median(side))
                yes = side > cut
                if 0 < yes.sum() < len(rows):
                    node = len(normals)
                    normals.append(normal)
                    offsets.append(cut)
                    children.append([0, 0])
                    children[node] = [build(rows[~yes]), build(rows[yes])]
                    return node
        leaves += 1
        return -leaves

    build(np.arange(len(sample)))
    dim = sample.shape[1]
    return Tree(np.array(normals).reshape(-1, dim), np.array(offsets), np.array(children, np.int64).reshape(-1, 2), max(leaves, 1))


def grow_forest(sample: np.ndarray, trees: int, leaf_rows: int, seed: int = 17) -> list[Tree]:
    return [grow(sample, leaf_rows, np.random.default_rng([seed, t])) for t in range(trees)]


def leaf_members(forest: list[Tree], sample: np.ndarray) -> list[list[np.ndarray]]:
    """Of each tree and leaf, the sample's rows that lie in it."""
    out = []
    for tree in forest:
        leaf = tree.leaf_of(sample)
        order = np.argsort(leaf, kind="stable")
        out.append(np.split(order, np.searchsorted(leaf[order], np.arange(1, tree.leaves))))
    return out


def probe(forest: list[Tree], members: list[list[np.ndarray]], x: np.ndarray, rows: int) -> tuple[list[tuple[int, int]], np.ndarray]:
    """The (tree, leaf) pairs that one query looks into, nearest first over all trees, until they hold `rows` distinct rows of the sample; and which rows.

    A place's distance is the largest margin by which the way to it was wrong. A leaf whose sample rows are all seen is looked into like any other.
    """
    queue: list[tuple[float, int, int]] = []
    sides = [t.normals @ x - t.offsets for t in forest]
    for t, tree in enumerate(forest):
        queue.append((0.0, t, 0 if len(tree.normals) else -1))
    heapq.heapify(queue)
    out, held = [], 0
    reached = np.zeros(sum(map(len, members[0])), bool)
    while queue and held < rows:
        wrong, t, node = heapq.heappop(queue)
        while node >= 0:
            side = sides[t][node]
            no, yes = forest[t].children[node].tolist()
            near, far = (yes, no) if side > 0 else (no, yes)
            heapq.heappush(queue, (max(wrong, abs(float(side))), t, far))
            node = near
        own = members[t][-node - 1]
        held += len(own) - int(reached[own].sum())
        reached[own] = True
        out.append((t, -node - 1))
    return out, reached
