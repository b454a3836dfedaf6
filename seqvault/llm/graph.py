"""Connected components, inside a task with numpy and across tasks with joins."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqvault.operators.barrier import barrier


def local_components(a: np.ndarray, b: np.ndarray, n: int) -> np.ndarray:
    """The smallest vertex number of each vertex's component, for edges ``a``-``b`` over 0..n-1."""
    label = np.arange(n)
    while len(a):
        la, lb = label[a], label[b]
        low = np.minimum(la, lb)
        np.minimum.at(label, la, low)
        np.minimum.at(label, lb, low)
        while True:  # follow labels to their roots
            up = label[label]
            if np.array_equal(up, label):
                break
            label = up
        differ = label[a] != label[b]
        a, b = a[differ], b[differ]
    return label


class Forest:
    """Components of the positions 0..n-1, merged lot by lot; knows which intervals lie in one component.

    Small lots are put aside until there are enough of them for a pass over all positions.
    """

    def __init__(self, n: int):
        self.labels = np.arange(n)
        self.reach = self.labels + 1  # first position after the run of equal labels
        self.aside: list[tuple[np.ndarray, np.ndarray]] = []
        self.held = 0

    def merge(self, a: np.ndarray, b: np.ndarray) -> None:
        self.aside.append((a, b))
        self.held += len(a)
        if self.held * 8 >= len(self.labels):
            self._settle()

    def _settle(self) -> None:
        if not self.held:
            return
        a, b = (self.labels[np.concatenate(x)] for x in zip(*self.aside, strict=True))
        self.aside, self.held = [], 0
        differ = a != b
        if not differ.any():
            return
        self.labels = local_components(a[differ], b[differ], len(self.labels))[self.labels]
        ends = np.append(np.flatnonzero(self.labels[1:] != self.labels[:-1]) + 1, len(self.labels))
        self.reach = np.repeat(ends, np.diff(ends, prepend=0))

    @property
    def label(self) -> np.ndarray:
        """The smallest position of each position's component."""
        self._settle()
        return self.labels

    def whole(self, pairs: np.ndarray) -> np.ndarray:
        """Which pairs of intervals (rows: first, end, first, end) are known to lie in one component."""
        al, ah, bl, bh = pairs[:4]
        return (self.labels[al] == self.labels[bl]) & (self.reach[al] >= ah) & (self.reach[bl] >= bh)


def connected_components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """``node``, ``component`` (smallest node reachable) for BIGINT edges ``a``, ``b``; nodes without edges are absent.

    Alternates two star steps: every neighbour above a node is linked to the smallest around that node, then every
    node's smaller neighbours are. Each step is a minimum per node, combined before the shuffle, joined back to the edges:
    rows of two numbers, and the side of the minima has one row a node, so Spark's skew handling can split a node with
    very many edges. The edges shrink to stars in about log(n) rounds; each round is written to the shared folder.
    Raises where ``most_rounds`` do not suffice.
    """
    current = barrier(_clean(edges), "edges")
    before = _state(current)
    for _ in range(most_rounds):
        if not before[0]:
            break
        both = current.unionByName(current.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("low")).select("a", F.least("low", "a").alias("low"))
        large = both.filter("b > a").join(low, "a").select(F.col("b").alias("a"), F.col("low").alias("b"))
        large = _clean(large)
        down = large.groupBy("a").agg(F.min("b").alias("low"))
        small = large.join(down, "a").select("b", "low").filter("b <> low").select(F.col("b").alias("a"), F.col("low").alias("b"))
        current = barrier(_clean(small.unionByName(down.select("a", F.col("low").alias("b")))), "edges")
        now = _state(current)
        if now == before:
            break
        before = now
    else:
        raise RuntimeError(f"components did not settle in {most_rounds} rounds")
    leaves = current.select(F.col("a").alias("node"), F.col("b").alias("component"))
    return leaves.unionByName(current.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())


def _state(edges: DataFrame) -> tuple:
    """Number and checksum of a set of edges."""
    return tuple(edges.agg(F.count("a"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())


def _clean(edges: DataFrame) -> DataFrame:
    """Distinct edges from the larger to the smaller node, without loops."""
    return edges.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
