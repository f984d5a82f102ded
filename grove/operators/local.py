"""Local work on whole components that share a task.

A task gets a number of whole components as flat arrays and solves them all at once,
level by level in numpy; only the greedy order is sequential. Components are placed
by packed bins, so what a task holds is bounded by their capacity."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from grove.operators.gather import binned
from grove.operators.graph import Forest
from grove.session import cut


class Arrays:
    """A forest as index arrays: ids rising, both directions of each edge, sorted by source."""

    def __init__(self, ids: np.ndarray, src: np.ndarray, dst: np.ndarray):
        self.ids = np.unique(ids)
        s, d = np.searchsorted(self.ids, src), np.searchsorted(self.ids, dst)
        order = np.argsort(s, kind="stable")
        self.src, self.dst = s[order], d[order]
        self.at = np.searchsorted(self.src, np.arange(len(self.ids) + 1))

    def neighbours(self, some: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(from, to) of all edges that leave ``some``."""
        n = self.at[some + 1] - self.at[some]
        at = np.repeat(self.at[some] - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())
        return np.repeat(some, n), self.dst[at]

    def walk(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(root, parent, depth) of each node; the root is its component's least id."""
        n = len(self.ids)
        root, parent, depth = np.full(n, -1), np.arange(n), np.zeros(n, np.int64)
        label = np.arange(n)
        while len(self.src):
            new = label.copy()
            np.minimum.at(new, self.src, label[self.dst])
            new = new[new]
            if (new == label).all():
                break
            label = new
        level = np.flatnonzero(label == np.arange(n))
        root[level] = level
        step = 0
        while len(level):
            a, b = self.neighbours(level)
            fresh = root[b] < 0
            a, b = a[fresh], b[fresh]
            root[b], parent[b] = root[a], a
            step += 1
            depth[b] = step
            level = np.unique(b)
        return root, parent, depth


def colours(t: Arrays, coin: Callable[[np.ndarray], np.ndarray]) -> np.ndarray:
    """One of the two 2-colourings of each component, picked by its leader's coin."""
    root, _, depth = t.walk()
    return (depth + coin(t.ids[root])) % 2 == 0


def greedy(t: Arrays) -> np.ndarray:
    """Maximal set by rising id."""
    state = np.zeros(len(t.ids), np.int8)
    for i in range(len(t.ids)):
        if not state[i]:
            state[i] = 1
            near = t.dst[t.at[i] : t.at[i + 1]]
            state[near[state[near] == 0]] = 2
    return state == 1


def larger_class(t: Arrays) -> np.ndarray:
    """The larger 2-colour class of each component; even depth wins ties."""
    root, _, depth = t.walk()
    odd = np.bincount(root, depth % 2, minlength=len(root))
    size = np.bincount(root, minlength=len(root))
    return np.where(odd[root] * 2 > size[root], depth % 2 == 1, depth % 2 == 0)


def maximum(t: Arrays) -> np.ndarray:
    """A maximum independent set of each tree, by levels from the deepest up."""
    _, parent, depth = t.walk()
    take, skip = np.ones(len(parent), np.int64), np.zeros(len(parent), np.int64)
    order = np.argsort(depth, kind="stable")
    cuts = np.searchsorted(depth[order], np.arange(depth.max(initial=0) + 2))
    for d in range(len(cuts) - 2, 0, -1):
        now = order[cuts[d] : cuts[d + 1]]
        np.add.at(take, parent[now], skip[now])
        np.add.at(skip, parent[now], np.maximum(take[now], skip[now]))
    chosen = np.zeros(len(parent), bool)
    for d in range(len(cuts) - 1):
        now = order[cuts[d] : cuts[d + 1]]
        free = ~chosen[parent[now]] | (parent[now] == now)
        chosen[now] = free & (take[now] > skip[now])
    # a node left out with no chosen neighbour can always join
    return _made_maximal(t, chosen)


def _made_maximal(t: Arrays, chosen: np.ndarray) -> np.ndarray:
    blocked = chosen.copy()
    blocked[t.dst[chosen[t.src]]] = True
    for i in np.flatnonzero(~blocked):
        if not chosen[i] and not chosen[t.dst[t.at[i] : t.at[i + 1]]].any():
            chosen[i] = True
    return chosen


SOLVERS = {"greedy": greedy, "colour": larger_class, "dp": maximum}


def per_task(g: Forest, labels: DataFrame, solve: Callable[[Arrays], dict[str, np.ndarray]], schema: str, capacity: int = 100_000) -> DataFrame:
    """Run ``solve`` on the arrays of each bin's components; its columns become rows.

    Components are packed into bins of at most ``capacity`` nodes (a larger one has its own bin),
    and a bin is a group of the plan, so its rows are whole whatever the planner does."""
    at = cut(binned(labels, capacity), "binned")
    rows = at.select("bin", F.col("v").alias("a"), F.col("v").alias("b")).unionByName(
        g.edges.join(at.select(F.col("v").alias("src"), "bin"), "src").select("bin", F.col("src").alias("a"), F.col("dst").alias("b"))
    )

    def run(t: pa.Table) -> pa.Table:
        a, b = t.column("a").to_numpy(), t.column("b").to_numpy()
        loop = a == b
        return pa.table(solve(Arrays(a[loop], a[~loop], b[~loop])))

    return rows.groupBy("bin").applyInArrow(run, schema)


def solve_components(g: Forest, labels: DataFrame, how: str) -> DataFrame:
    """(v): the union of local solutions, one of SOLVERS for each component."""

    def solve(t: Arrays) -> dict[str, np.ndarray]:
        return {"v": t.ids[SOLVERS[how](t)]}

    return per_task(g, labels, solve, "v long")
