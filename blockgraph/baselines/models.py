"""Other programming models: vertex-, edge- and block-centric rounds, and linear algebra over semirings."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans import packed
from ..plans.blocks import BlockedGraph
from ..plans.store import stored
from ..algorithms.components import components_hook


def vertex_program(edges: DataFrame, state: DataFrame, send: Column, merge: Callable, update: Column, max_rounds: int = 1000) -> DataFrame:
    """Rounds of messages along directed edges. State: (id, value). ``send`` is a column over value (and edge columns), ``merge``
    an aggregate of ``message``, ``update`` a column over value and message; it ends when no value changes."""
    for _ in range(max_rounds):
        messages = edges.join(state.withColumnRenamed("id", "src"), "src").select(F.col("dst").alias("id"), send.alias("message"))
        merged = messages.groupBy("id").agg(merge("message").alias("message"))
        new = stored(state.join(merged, "id", "left").select("id", update.alias("value"), F.col("value").alias("old")), "vertex-round")
        state = new.select("id", "value")
        if not new.where("not (value <=> old)").limit(1).count():
            break
    return state


def edge_program(edges: DataFrame, state: DataFrame, fn: Column, merge: Callable, max_rounds: int = 1000) -> DataFrame:
    """Every round scans all edges with the values of both ends (a, b): ``fn`` is the offer to the edge's destination; the merged offers and the old value are merged again."""
    for _ in range(max_rounds):
        both = edges.join(state.select(F.col("id").alias("src"), F.col("value").alias("a")), "src").join(state.select(F.col("id").alias("dst"), F.col("value").alias("b")), "dst")
        offers = both.select(F.col("dst").alias("id"), fn.alias("value")).unionByName(state)
        new = stored(offers.groupBy("id").agg(merge("value").alias("value")).join(state.withColumnRenamed("value", "old"), "id"), "edge-round")
        state = new.select("id", "value")
        if not new.where("not (value <=> old)").limit(1).count():
            break
    return state


#: Edges of which the forests are found at a time.
PIECE = 1 << 19
#: Edges and links of a carried forest that a task holds.
CARRIED = 1 << 21


def _forest(src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Links (a, b) that join every vertex to the least one it is connected with: roots are hooked below lesser ones, and pointers jump."""
    names, at = np.unique(np.concatenate([src, dst]), return_inverse=True)
    a, b, root = at[: len(src)], at[len(src) :], np.arange(len(names))
    while len(a):
        ra, rb = root[a], root[b]
        apart = ra != rb
        a, b, ra, rb = a[apart], b[apart], ra[apart], rb[apart]
        np.minimum.at(root, np.maximum(ra, rb), np.minimum(ra, rb))
        while (jumped := root[root]).tobytes() != root.tobytes():
            root = jumped
    moved = root != np.arange(len(names))
    return names[root[moved]], names[moved]


def _forests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Forests of the blocks' parts that lie together, a bounded number of edges at a time: what a part joins, its forest joins."""

    def solve(parts: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block, src, dst = (np.concatenate([b.column(k).to_numpy(zero_copy_only=False) for b in parts]) for k in range(3))
        order = np.argsort(block, kind="stable")
        for mine in np.split(order, np.flatnonzero(np.diff(block[order])) + 1):
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in _forest(src[mine], dst[mine])], ["src", "dst"])

    parts, held = [], 0
    for batch in batches:
        if batch.num_rows:
            parts.append(batch)
            held += batch.num_rows
        if held >= PIECE:
            yield from solve(parts)
            parts, held = [], 0
    if held:
        yield from solve(parts)


def _carried(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One forest of all edges of a task, carried from part to part; a forest too large to be carried is sent on, and a new one begins."""
    told = lambda links: pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in links], ["src", "dst"])
    parts, held = [], 0
    for batch in batches:
        if batch.num_rows:
            parts.append(tuple(batch.column(k).to_numpy(zero_copy_only=False) for k in range(2)))
            held += batch.num_rows
        if held >= CARRIED:
            parts = [_forest(*(np.concatenate(x) for x in zip(*parts, strict=True)))]
            held = len(parts[0][0])
            if 8 * held > 7 * CARRIED:
                yield told(parts[0])
                parts, held = [], 0
    if held:
        yield told(_forest(*(np.concatenate(x) for x in zip(*parts, strict=True))))


def forest_links(edges: DataFrame) -> DataFrame:
    """Links (src, dst) that join what the edges without loops join, and no vertex less: forests of the edges, found where these lie, by as many tasks as run at once."""
    return edges.select("src", "dst").coalesce(max(1, edges.sparkSession.sparkContext.defaultParallelism)).mapInArrow(_carried, "src long, dst long")


def block_local_components(graph: BlockedGraph) -> DataFrame:
    """Components solved inside the blocks first, where their parts lie, so that no block has to fit a task; only spanning forests go into the global rounds."""
    forest = graph.blocks.select("block_id", "src", "dst").mapInArrow(_forests, "src long, dst long").distinct()
    return components_hook(stored(forest, "forest"), graph.vertices.select("id"))


SEMIRINGS: dict[str, tuple[Callable, Callable]] = {
    "plus_times": (F.sum, lambda a, b: a * b),
    "min_plus": (F.min, lambda a, b: a + b),
    "or_and": (F.max, lambda a, b: F.least(a, b)),
}


def spmv(matrix: DataFrame, vector: DataFrame, semiring: str = "plus_times") -> DataFrame:
    """(id, value) of matrix (row, col, val) times vector (id, value)."""
    add, times = SEMIRINGS[semiring]
    joined = matrix.join(vector.withColumnRenamed("id", "col"), "col")
    return joined.groupBy(F.col("row").alias("id")).agg(add(times(F.col("val"), F.col("value"))).alias("value"))


def spgemm_masked(a: DataFrame, b: DataFrame, mask: DataFrame, semiring: str = "plus_times") -> DataFrame:
    """(row, col, val) of a times b, only where ``mask`` has an entry."""
    add, times = SEMIRINGS[semiring]
    right = b.select(F.col("row").alias("k"), "col", F.col("val").alias("bv"))
    product = a.select("row", F.col("col").alias("k"), F.col("val").alias("av")).join(right, "k").join(mask.select("row", "col"), ["row", "col"], "left_semi")
    return product.groupBy("row", "col").agg(add(times(F.col("av"), F.col("bv"))).alias("val"))


def spgemm_masked_total(a: DataFrame, b: DataFrame, mask: DataFrame) -> DataFrame:
    """One row (total): the sum of all entries of a times b where ``mask`` has an entry. Where there are many, blocks of the matrices are
    multiplied in packed kernels, so that single products are never shuffled."""
    if mask.count() >= packed.MANY_EDGES:
        return packed.masked_total(a, b, mask)
    return spgemm_masked(a, b, mask).agg(F.coalesce(F.sum("val"), F.lit(0.0)).alias("total"))
