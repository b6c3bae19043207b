"""Breadth-first search as a block program over activated lists, and shortest paths.

A block is (stripe of the frontier -> stripe of the targets). Each level composes lists from the blocks whose source stripe holds a
part of the frontier. The light kernel goes top-down: frontier rows join the edges of their block. The heavy one goes
bottom-up through the mirrored block in Arrow batches: unvisited targets look through their neighbours in order and stop
at the first in the frontier. A block's discoveries are the same either way, so lanes and directions mix without a loss. Parents are the
least neighbour on the level before.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.blocks import BlockedGraph, sizes_of
from ..plans.program import BlockProgram, Context, run
from ..plans.store import stored

#: top-down; bottom-up; one of them for a level, by its work; bottom-up on the heavy lists of a level and top-down on the light ones.
DIRECTIONS = ("down", "up", "auto", "by_lane")
#: Levels after which the tree so far is written as one table.
LEVELS_PER_TABLE = 8
#: Most ids of a bitmap that goes to the workers (32 MB); graphs with a wider range of ids go up by joins.
MOST_BITS = 1 << 28
#: Neighbours that are tried one by one before a vertex looks through the rest at once.
SINGLE_TRIES = 32


def _bitmap(ids: DataFrame, low: int, width: int) -> np.ndarray:
    """A bit per id from ``low`` on, built by Spark; at most width / 32768 rows of 4 KB reach the driver."""
    slot = ids.select((F.col("id") - low + 1).alias("s"))
    rows = slot.groupBy(F.bitmap_bucket_number("s").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("s")).alias("bits"))
    out = np.zeros(-(-width // 32768) * 4096, np.uint8)
    for row in rows.toLocalIterator():
        out[(row.bucket - 1) * 4096 : row.bucket * 4096] = np.frombuffer(bytes(row.bits), np.uint8)
    return out


def _has(bits: np.ndarray, at: np.ndarray) -> np.ndarray:
    return (bits[at >> 3] >> (at & 7).astype(np.uint8) & 1).astype(bool)


def edges_from(edges: DataFrame, ids: DataFrame) -> DataFrame:
    """The edges (src, dst) whose source is among the ids. They stay where they are, as long as a bitmap of the ids fits."""
    span = ids.agg(F.min("id").alias("low"), F.max("id").alias("high")).first()
    if span.low is None or span.high - span.low > MOST_BITS:
        return edges.join(ids.select(F.col("id").alias("src")), "src", "left_semi")
    low, width = span.low, span.high - span.low + 1
    bits = edges.sparkSession.sparkContext.broadcast(_bitmap(ids.select("id"), low, width))

    def run_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            src = batch.column(0).to_numpy(zero_copy_only=False)
            there = np.flatnonzero((src >= low) & (src < low + width))
            keep = there[_has(bits.value, src[there] - low)]
            if len(keep):
                yield batch.take(pa.array(keep))

    return edges.select("src", "dst").mapInArrow(run_batches, "src long, dst long")


def first_in_frontier(starts: np.ndarray, ends: np.ndarray, dst: np.ndarray, frontier: np.ndarray) -> tuple[np.ndarray, int]:
    """For each run of neighbours the place of the first one in the frontier (-1: none), and how many were looked at.

    A run that has found one is left alone, as are the neighbours behind it.
    """
    found, read = np.full(len(starts), -1, np.int64), 0
    open_ = np.arange(len(starts))
    for k in range(SINGLE_TRIES):
        open_ = open_[starts[open_] + k < ends[open_]]
        if not len(open_):
            return found, read
        at = starts[open_] + k
        read += len(at)
        hit = _has(frontier, dst[at])
        found[open_[hit]] = at[hit]
        open_ = open_[~hit]
    for i in open_.tolist():  # long runs
        at = starts[i] + SINGLE_TRIES
        hit = np.flatnonzero(_has(frontier, dst[at : ends[i]]))
        found[i] = at + hit[0] if len(hit) else -1
        read += int(hit[0]) + 1 if len(hit) else int(max(0, ends[i] - at))
    return found, read


def _look_up(frontier, visited, low: int):
    def run_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, settled = None, False  # of the run that the batch before ended in
        for batch in batches:
            if not batch.num_rows:
                continue
            src, dst = (batch.column(c).to_numpy(zero_copy_only=False) - low for c in ("src", "dst"))
            begins = np.flatnonzero(np.diff(src, prepend=src[0] - 1))
            ends = np.append(begins[1:], len(src))
            free = ~_has(visited.value, src[begins])
            free[0] &= not (settled and last == src[0])
            found, read = first_in_frontier(begins[free], ends[free], dst, frontier.value)
            hit = found >= 0
            ids, parents = src[begins[free][hit]] + low, dst[found[hit]] + low
            settled = (settled and last == src[-1]) or bool(len(ids) and ids[-1] - low == src[-1])
            last = src[-1]
            # A row without an id carries the number of edges read.
            yield pa.RecordBatch.from_arrays([pa.array([*ids.tolist(), None], pa.int64()), pa.array([*parents.tolist(), None], pa.int64()), pa.array([*[0] * len(ids), read], pa.int64())], ["id", "parent", "read"])

    return run_batches


def _down(ctx: Context, edges: DataFrame) -> DataFrame:
    """Top-down: the frontier's edges offer their source as parent. Every edge of the frontier in these blocks is read."""
    near = edges.join(ctx.globals["frontier"].select(F.col("id").alias("src")), "src")
    return near.groupBy(F.col("dst").alias("id")).agg(F.min("src").alias("parent"), F.count("*").alias("read"))


def _mirrored(ctx: Context, edges: DataFrame) -> DataFrame:
    """The blocks (j, i) of the lists over blocks (i, j)."""
    blocks = ctx.graph.blocks
    if ctx.graph.layout == "1d":
        return blocks
    blocks = blocks.where(F.col("col").isin(ctx.globals["stripes"]))
    if ctx.lane != "both":
        return blocks
    mine = edges.select("row", "col").distinct()  # p^2 rows at most
    return blocks.join(F.broadcast(mine.select(F.col("col").alias("row"), F.col("row").alias("col"))), ["row", "col"], "left_semi")


def _up(ctx: Context, edges: DataFrame) -> DataFrame:
    """Bottom-up with an early stop, in Arrow batches; by joins where the range of ids is too wide for bitmaps."""
    blocks = _mirrored(ctx, edges)
    bits = ctx.globals.get("bits")
    if bits is None:
        free = blocks.join(ctx.state.select(F.col("id").alias("src")), "src", "left_anti")
        near = free.join(ctx.globals["frontier"].select(F.col("id").alias("dst"), F.lit(True).alias("hit")), "dst", "left")
        return near.groupBy(F.col("src").alias("id")).agg(F.min(F.when(F.col("hit"), F.col("dst"))).alias("parent"), F.count("*").alias("read"))
    return blocks.select("src", "dst").mapInArrow(_look_up(*bits), "id long, parent long, read long")


def bfs(graph: BlockedGraph, source=0, direction: str = "auto", alpha: float = 14.0, beta: float = 24.0, max_levels: int = 100_000, log: list | None = None) -> DataFrame:
    """(id, parent, level) of everything reached from the source (or list of sources). A source is its own parent.

    ``auto`` goes up once the frontier's edges times ``alpha`` pass those of unvisited vertices, and down again once
    the frontier has fewer vertices than all divided by ``beta``. ``log`` receives (level, step, count) rows, among them the edges read.
    """
    if direction not in DIRECTIONS:
        raise ValueError(f"unknown direction {direction!r}")
    sources = [source] if isinstance(source, int) else list(source)
    low, high = graph.cuts.bounds[0], graph.cuts.bounds[-1]
    start = stored(graph.vertices.where(F.col("id").isin(sources)).select("id", F.col("id").alias("parent"), F.lit(0).alias("level")), "visited")
    blocks = graph.blocks
    if direction != "down" and not graph.kept:
        blocks = blocks.repartition("src").sortWithinPartitions("src", "dst")  # neighbours in order, for the early stop
    graph = BlockedGraph(blocks, sizes_of(blocks), graph.vertices, graph.cuts, graph.layout, graph.kept)
    spark = blocks.sparkSession
    mapped = direction != "down" and high - low <= MOST_BITS
    first = start.select(graph.cuts.stripe("id").alias("stripe")).distinct().collect()  # p rows at most
    ctx = Context(graph, start, lane={"down": "light", "up": "heavy", "auto": "light", "by_lane": "both"}[direction])
    ctx.globals |= {"frontier": start.select("id"), "stripes": [r.stripe for r in first]}
    degree = None
    if direction == "auto":
        degree = stored(blocks.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("degree")), "degrees")
        total = degree.agg(F.count("*").alias("n"), F.coalesce(F.sum("degree"), F.lit(0)).alias("e")).first()
        mine = degree.join(start, "id").agg(F.count("*").alias("n"), F.coalesce(F.sum("degree"), F.lit(0)).alias("e")).first()
        ctx.globals |= {"n": mine.n, "e": mine.e, "free": total.e}

    def before(ctx: Context) -> None:
        if direction == "auto":
            n, mine = ctx.globals["n"], ctx.globals["e"]
            ctx.globals["free"] -= mine
            up = mine * alpha > ctx.globals["free"] if ctx.lane == "light" else n * beta >= total.n
            ctx.lane = "heavy" if up else "light"
        if log is not None:
            log.append((ctx.round, {"light": "down", "heavy": "up", "both": "both"}[ctx.lane], len(ctx.globals["stripes"])))
        if mapped and ctx.lane != "light":
            bits = [spark.sparkContext.broadcast(_bitmap(x.select("id"), low, high - low + 1)) for x in (ctx.globals["frontier"], ctx.state)]
            ctx.globals["bits"] = (*bits, low)

    def after(ctx: Context, updates: DataFrame) -> bool:
        seen = ctx.state.select("id", F.lit(True).alias("seen"))
        merged = updates.groupBy("id").agg(F.min("parent").alias("parent"), F.sum("read").alias("read")).join(seen, "id", "left")
        fresh = F.col("id").isNotNull() & F.col("parent").isNotNull() & F.col("seen").isNull()
        merged = merged.select("id", "parent", F.lit(ctx.round + 1).alias("level"), "read", fresh.alias("fresh"))
        level = stored(merged if degree is None else merged.join(degree, "id", "left"), "level")
        work = [F.sum("read").alias("read"), F.sum(F.col("fresh").cast("long")).alias("n")] + ([F.sum(F.when(F.col("fresh"), F.col("degree"))).alias("e")] if degree is not None else [])
        rows = level.groupBy(F.when(F.col("fresh"), graph.cuts.stripe("id")).alias("stripe")).agg(*work).collect()  # p + 1 rows at most
        if log is not None:
            log.append((ctx.round, "edges", sum(r.read for r in rows)))
        ctx.globals["stripes"] = [r.stripe for r in rows if r.n]
        if degree is not None:
            ctx.globals |= {"n": sum(r.n for r in rows), "e": sum(r.e or 0 for r in rows)}
        new = level.where("fresh").select("id", "parent", "level")
        ctx.globals["frontier"] = new.select("id")
        if not ctx.globals["stripes"]:
            return False
        ctx.state = ctx.state.unionByName(new)
        if (ctx.round + 1) % LEVELS_PER_TABLE == 0:
            ctx.state = stored(ctx.state, "visited")
        return ctx.round + 1 < max_levels

    program = BlockProgram(light=_down, heavy=_up, active=lambda ctx: ctx.globals["stripes"], before=before, after=after, lazy=True)
    return run(program, graph, start, ctx=ctx).state if max_levels > 0 and first else start


def level_histogram(tree: DataFrame) -> DataFrame:
    return tree.groupBy("level").agg(F.count("*").alias("vertices"))


def shortest_paths(graph: BlockedGraph, source: int, weight_col: str | None = None, max_rounds: int = 100_000) -> DataFrame:
    """(id, dist, parent) for weights of 0 or more: only vertices whose distance fell in the round before relax their edges, in the
    blocks of their stripes. A parent is the least neighbour that is nearer; over an edge of weight 0, the least one with fewer hops."""
    w = F.col(weight_col).cast("double") if weight_col else F.lit(1.0)
    best = stored(graph.vertices.where(F.col("id") == source).select("id", "stripe", F.lit(0.0).alias("dist"), F.lit(0).alias("hops"), F.lit(True).alias("fresh")), "distances")
    for _ in range(max_rounds):
        fresh = best.where("fresh")
        stripes = [r.stripe for r in fresh.select("stripe").distinct().collect()]  # p at most
        if not stripes:
            break
        active = graph.blocks.where(F.col("row").isin(stripes)).select("src", "dst", w.alias("w"))
        offers = active.join(fresh.select(F.col("id").alias("src"), "dist", "hops"), "src").groupBy(F.col("dst").alias("id")).agg(F.min(F.struct((F.col("dist") + F.col("w")).alias("dist"), (F.col("hops") + 1).alias("hops"))).alias("offer"))
        merged = best.select("id", F.struct("dist", "hops").alias("old")).join(offers, "id", "full_outer").join(graph.vertices, "id")
        better = F.col("offer").isNotNull() & (F.col("old").isNull() | (F.col("offer") < F.col("old")))
        chosen = F.when(better, F.col("offer")).otherwise(F.col("old"))
        best = stored(merged.select("id", "stripe", chosen["dist"].alias("dist"), chosen["hops"].alias("hops"), better.alias("fresh")), "distances")
    # The least neighbour through which the distance is reached exactly as it was summed, in as many hops.
    edges = graph.blocks.select("src", "dst", w.alias("w"))
    via = edges.join(best.select(F.col("id").alias("src"), F.col("dist").alias("d"), F.col("hops").alias("h")), "src").join(best.select(F.col("id").alias("dst"), "dist", "hops"), "dst")
    parents = via.where("d + w = dist and h + 1 = hops").groupBy(F.col("dst").alias("id")).agg(F.min("src").alias("parent"))
    return best.join(parents, "id", "left").select("id", "dist", F.when(F.col("id") == source, F.col("id")).otherwise(F.col("parent")).alias("parent"))
