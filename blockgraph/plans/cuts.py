"""Cut vectors over vertex ids: stripe i holds the ids in [cut i, cut i+1).

Cuts are computed on the driver from a histogram of at most ``BUCKETS`` id ranges, never from the edges themselves.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BUCKETS = 1 << 16


@dataclass(frozen=True)
class Cuts:
    """p + 1 bounds in rising order; ids beyond the outer ones fall into the outer stripes."""

    bounds: tuple[int, ...]

    @property
    def p(self) -> int:
        return len(self.bounds) - 1

    def stripe(self, column: Column | str) -> Column:
        """Number of the stripe an id lies in, as a balanced tree of comparisons."""
        x = F.col(column) if isinstance(column, str) else column

        def tree(low: int, high: int) -> Column:
            if high - low == 1:
                return F.lit(low)
            mid = (low + high) // 2
            return F.when(x < self.bounds[mid], tree(low, mid)).otherwise(tree(mid, high))

        return tree(0, self.p)

    def table(self, spark) -> DataFrame:
        rows = [(i, a, b) for i, (a, b) in enumerate(zip(self.bounds, self.bounds[1:], strict=False))]
        return spark.createDataFrame(rows, "stripe int, lo long, hi long")


def id_range(edges: DataFrame) -> tuple[int, int]:
    row = edges.agg(F.min(F.least("src", "dst")).alias("a"), F.max(F.greatest("src", "dst")).alias("b")).first()
    return (0, 0) if row.a is None else (int(row.a), int(row.b))


def histogram(edges: DataFrame, buckets: int = BUCKETS) -> tuple[np.ndarray, int, int]:
    """Edge ends per id range, the least id and the width of a range."""
    low, high = id_range(edges)
    width = max(1, -(-(high - low + 1) // buckets))
    ends = edges.select(F.explode(F.array("src", "dst")).alias("id"))
    counts = np.zeros(-(-(high - low + 1) // width), np.int64)
    for row in ends.groupBy(F.floor((F.col("id") - low) / width).alias("b")).agg(F.count("*").alias("n")).toLocalIterator():
        counts[row.b] = row.n
    return counts, low, width


def uniform(edges: DataFrame, p: int) -> Cuts:
    """Equal id ranges from 0 (or the least id, if negative): stripe = id p div (max + 1)."""
    low, high = id_range(edges)
    low = min(low, 0)
    return Cuts(tuple(low + -(-i * (high + 1 - low) // p) for i in range(p + 1)))


def optimal_1d(loads, p: int) -> list[int]:
    """Starts of p contiguous groups whose greatest sum is least (bisection over the greedy test)."""
    loads = np.asarray(loads, np.int64)
    sums = np.concatenate([[0], np.cumsum(loads)])

    def pack(limit: int) -> list[int] | None:
        starts, at = [0], 0
        for _ in range(p - 1):
            at = int(np.searchsorted(sums, sums[at] + limit, "right")) - 1
            starts.append(at)
        return starts if sums[-1] - sums[at] <= limit else None

    low, high = int(loads.max(initial=0)), int(sums[-1])
    while low < high:
        mid = (low + high) // 2
        low, high = (low, mid) if pack(mid) else (mid + 1, high)
    return [*pack(low), len(loads)]


def optimal_1d_exact(loads, p: int) -> int:
    """The least greatest sum, by dynamic programming (for tests)."""
    sums = np.concatenate([[0], np.cumsum(loads)])
    n = len(loads)
    best = [int(sums[i]) for i in range(n + 1)]
    for _ in range(p - 1):
        best = [min(max(best[j], int(sums[i] - sums[j])) for j in range(i + 1)) for i in range(n + 1)]
    return best[n]


def balanced(edges: DataFrame, p: int) -> Cuts:
    """Stripes with even numbers of edge ends."""
    counts, low, width = histogram(edges)
    return Cuts(tuple(low + width * s for s in optimal_1d(counts, p)))


def loaded(nodes: DataFrame, load: str, p: int) -> Cuts:
    """Stripes with even sums of a load of the vertices, whose ``id`` runs from 0 without gaps."""
    n = nodes.count()
    width = max(1, -(-n // BUCKETS))
    sums = np.zeros(max(1, -(-n // width)), np.int64)
    for row in nodes.groupBy(F.floor(F.col("id") / width).alias("b")).agg(F.sum(load).alias("s")).toLocalIterator():
        sums[row.b] = row.s
    return Cuts(tuple(width * s for s in optimal_1d(sums, p)))


def refined(edges: DataFrame, p: int, grid: int = 256) -> Cuts:
    """Symmetric cuts whose greatest block is small: stripes are stretched greedily under a limit on blocks found by bisection.

    Works on a ``grid`` x ``grid`` count matrix over ranges of even load.
    """
    start = balanced(edges, min(grid, BUCKETS))
    a, b = start.stripe("src"), start.stripe("dst")
    m = np.zeros((start.p, start.p), np.int64)
    for row in edges.groupBy(a.alias("i"), b.alias("j")).agg(F.count("*").alias("n")).toLocalIterator():
        m[row.i, row.j] += row.n
        m[row.j, row.i] += row.n
    s = np.zeros((start.p + 1, start.p + 1), np.int64)
    s[1:, 1:] = m.cumsum(0).cumsum(1)

    def pack(limit: int) -> list[int] | None:
        at = [0]
        for _ in range(p):
            c, e = at[-1], start.p
            if c == e:
                at.append(e)
                continue

            def fits(end: int) -> bool:
                if s[end, end] - s[c, end] - s[end, c] + s[c, c] > limit:
                    return False
                return all(s[end, y] - s[c, y] - s[end, x] + s[c, x] <= limit for x, y in zip(at, at[1:], strict=False))

            low, high = c + 1, e
            if not fits(low):
                return None
            while low < high:
                mid = (low + high + 1) // 2
                low, high = (mid, high) if fits(mid) else (low, mid - 1)
            at.append(low)
        return at if at[-1] == start.p else None

    low, high = 1, max(1, int(m.sum()))
    while low < high:
        mid = (low + high) // 2
        low, high = (low, mid) if pack(mid) else (mid + 1, high)
    return Cuts(tuple(start.bounds[i] for i in pack(low)))


def custom(bounds) -> Cuts:
    bounds = tuple(int(b) for b in bounds)
    if len(bounds) < 2 or any(a > b for a, b in zip(bounds, bounds[1:], strict=False)):
        raise ValueError("cuts must rise")
    return Cuts(bounds)


def is_conformal(a: Cuts, b: Cuts) -> bool:
    """Whether the output stripes of one partition are the input stripes of the other."""
    return a.bounds == b.bounds


METHODS = {"uniform": uniform, "balanced": balanced, "refined": refined}


def symmetric(edges: DataFrame, p: int, method: str = "uniform") -> Cuts:
    if method not in METHODS:
        raise ValueError(f"unknown cuts {method!r}")
    return METHODS[method](edges, p)
