"""Block programs and their runtime: lists, weights, lanes, rounds with hooks, and merged updates."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from contextlib import contextmanager, nullcontext
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import planner
from .blocklists import compose_where, lists_active, lists_single, members
from .blocks import BlockedGraph
from .packed import LISTS_PER_JOB
from .store import side_by_side, stored

COMBINERS = {"sum": F.sum, "min": F.min, "max": F.max, "first_wins": F.min}
#: Jobs submitted together, one for each lane and wave at most.
MAX_JOBS = 4


@dataclass
class Context:
    """What hooks and kernels see: the graph, the state table, scalars, the round, and the log."""

    graph: BlockedGraph
    state: DataFrame | None = None
    globals: dict = field(default_factory=dict)
    round: int = 0
    lane: str = "light"
    log: list = field(default_factory=list)

    def vertices(self, side: str = "src") -> DataFrame:
        """(block_id, id) of the sources or destinations of every block."""
        return self.graph.blocks.select("block_id", F.col(side).alias("id")).distinct()

    def neighbours(self, source: int) -> DataFrame:
        return self.graph.blocks.where(F.col("src") == source).select("block_id", "dst")

    def note(self, step: str, counter: str, value: float, lists: int = 0, seconds: float = 0.0) -> None:
        self.log.append((self.round, step, lists, counter, float(value), float(seconds)))


@dataclass
class BlockProgram:
    """A computation over block lists.

    ``light(ctx, edges)`` and ``heavy(ctx, edges)`` return update rows for the edges of their lists (with ``list_id`` and
    ``position``); one may be absent. Lists come from ``lists(ctx)`` or from a predicate (``lists_where`` with ``size``).
    ``before(ctx)`` runs ahead of a round; ``after(ctx, updates)`` behind it, and tells whether another follows.
    ``active(ctx)`` names the stripes whose rows of blocks make the lists of a round. ``static`` lists are planned once. ``lazy`` updates are not stored: ``after`` gets them as a plan and may let several
    rounds grow into one job.
    """

    light: Callable | None = None
    heavy: Callable | None = None
    lists: Callable | None = None
    lists_where: str | None = None
    before: Callable | None = None
    after: Callable | None = None
    weight: str = "n_edges"
    size: int = 1
    static: bool = False
    lazy: bool = False
    active: Callable | None = None

    def __post_init__(self) -> None:
        if self.light is None and self.heavy is None:
            raise ValueError("a program needs a light or a heavy kernel")
        if self.active:
            self.lists = lambda ctx: lists_active(ctx.graph.manifest, self.active(ctx)) if ctx.graph.layout == "2d" else single(ctx)
        if self.lists is None and self.lists_where is None:
            raise ValueError("a program needs lists or a predicate for lists")


def plan(program: BlockProgram, ctx: Context, lane: str = "light", bins: int | None = None, budget_bytes: int | None = None, cutoff: float | None = None) -> DataFrame:
    """The list table of a round: list_id, blocks, weight, bytes, lane[, bin][, wave]."""
    made = program.lists(ctx) if program.lists else compose_where(ctx.graph.manifest, program.size, program.lists_where)
    if lane == "light" and program.light is None:
        lane = "heavy"
    if lane == "heavy" and program.heavy is None:
        lane = "light"
    both = program.light is not None and program.heavy is not None
    placed = planner.split(planner.weigh(made, ctx.graph.manifest, program.weight), lane if both or lane != "both" else ("light" if program.light else "heavy"), cutoff=cutoff)
    if bins:
        placed = planner.bins_lpt(placed, bins)
    return planner.waves(placed, budget_bytes) if budget_bytes else placed


def edges_of(ctx: Context, lists: DataFrame) -> DataFrame:
    """Edges with the list and position they serve. Lists are planning-size, so they are broadcast while Spark finds them small."""
    return ctx.graph.blocks.join(members(lists), "block_id")


def edges_of_list(ctx: Context, list_id: int, blocks: list[int]) -> DataFrame:
    """The edges of one list with their positions, read from the folders of its blocks into one partition, so that no kernel shuffles them."""
    at = [ctx.graph.block(b).withColumns({"list_id": F.lit(list_id).cast("long"), "position": F.lit(k)}) for k, b in enumerate(blocks)]
    return reduce(DataFrame.unionAll, at).coalesce(1)


def within_list(rows: DataFrame) -> DataFrame:
    """What a kernel has joined of one list's edges, told to be in one partition still: a further join would shuffle it otherwise."""
    return rows.coalesce(1)


@contextmanager
def lists_stay(spark: SparkSession) -> Iterator[None]:
    """Joins of single partitions stay there, however large Spark thinks them."""
    name = "spark.sql.maxSinglePartitionBytes"
    before = spark.conf.get(name)
    spark.conf.set(name, str(1 << 62))
    try:
        yield
    finally:
        spark.conf.set(name, before)


def updates_of(ctx: Context, kernel: Callable, edges: DataFrame | list[DataFrame]) -> DataFrame:
    """Stored updates of a kernel, over the edges of all lists at once or of every list by itself, a task a list."""
    if isinstance(edges, DataFrame):
        return stored(kernel(ctx, edges), "updates")
    jobs = [edges[k : k + LISTS_PER_JOB] for k in range(0, len(edges), LISTS_PER_JOB)]
    return reduce(DataFrame.unionAll, [stored(side_by_side([kernel(ctx, e) for e in job]), "updates") for job in jobs])


def merge(updates: DataFrame, on: list[str], value: str, combiner: str | None) -> DataFrame:
    """One row per key. Without a combiner, two updates of a key are an error."""
    if combiner is None:
        checked = updates.groupBy(*on).agg(F.first(value).alias(value), F.count("*").alias("_n"))
        return checked.withColumn(value, F.when(F.col("_n") > 1, F.raise_error(F.lit("several updates of a key and no combiner"))).otherwise(F.col(value))).drop("_n")
    if combiner not in COMBINERS:
        raise ValueError(f"unknown combiner {combiner!r}")
    return updates.groupBy(*on).agg(COMBINERS[combiner](value).alias(value))


def par_for(df: DataFrame, body: Callable) -> DataFrame:
    """A function over all rows: columns in, columns out."""
    return df.select(*body(df))


def par_reduce(df: DataFrame, body, combine: str):
    """One value over all rows."""
    return df.agg(COMBINERS[combine](body).alias("value")).first()["value"]


def submit_lanes(jobs: list[Callable], max_jobs: int = MAX_JOBS) -> list:
    """Run a few jobs at a time and return their results in order."""
    with ThreadPoolExecutor(max_workers=max(1, min(max_jobs, len(jobs)))) as pool:
        return [f.result() for f in [pool.submit(j) for j in jobs]]


def _parts(program: BlockProgram, ctx: Context, planning: dict) -> list[tuple[Callable, DataFrame | list[DataFrame]]]:
    """Kernels with the edges of their lists, list by list where blocks lie in folders. Where all blocks go to one lane alone, there is nothing to plan."""
    if ctx.lane != "both" and (program.active or program.lists is single) and not planning:
        kernel = program.light if program.heavy is None or (ctx.lane == "light" and program.light) else program.heavy
        rows = program.active(ctx) if program.active and ctx.graph.layout == "2d" else None
        return [(kernel, ctx.graph.blocks if rows is None else ctx.graph.blocks.where(F.col("row").isin(rows)))]
    lists = stored(plan(program, ctx, ctx.lane, **planning), "lists")
    waves = [r.wave for r in lists.select("wave").distinct().orderBy("wave").collect()] if "wave" in lists.columns else [None]
    parts = []
    for name, kernel in (("light", program.light), ("heavy", program.heavy)):
        for wave in waves if kernel else ():
            mine = lists.where(F.col("lane") == name)
            mine = mine if wave is None else mine.where(F.col("wave") == wave)
            alone = [edges_of_list(ctx, r.list_id, r.blocks) for r in mine.orderBy(F.desc("weight"), "list_id").collect()] if ctx.graph.path and not program.lazy else []
            parts.append((kernel, alone or edges_of(ctx, mine.select("list_id", "blocks"))))
    return parts


def run(program: BlockProgram, graph: BlockedGraph, state: DataFrame | None = None, lane: str = "light", max_rounds: int = 1_000_000, ctx: Context | None = None, **planning) -> Context:
    """Rounds until ``after`` says stop (one round without it). Lanes and waves of a round are separate jobs, unless updates are lazy; updates are their union."""
    if lane not in planner.LANES:
        raise ValueError(f"unknown lane {lane!r}")
    ctx = ctx or Context(graph, state, lane=lane)
    parts = None
    while ctx.round < max_rounds:
        began = time.time()
        if program.before:
            program.before(ctx)
        parts = parts if program.static and parts else _parts(program, ctx, planning)
        if program.lazy:
            done = [kernel(ctx, edges) for kernel, edges in parts]
        else:
            with lists_stay(graph.manifest.sparkSession) if graph.path else nullcontext():
                done = submit_lanes([lambda kernel=kernel, edges=edges: updates_of(ctx, kernel, edges) for kernel, edges in parts])
        updates = done[0]
        for more in done[1:]:
            updates = updates.unionByName(more)
        ctx.globals["updates"] = updates
        go_on = bool(program.after and program.after(ctx, updates))
        ctx.note("round", "seconds", time.time() - began, lists=len(parts), seconds=time.time() - began)
        ctx.round += 1
        if not go_on:
            break
    return ctx


def single(ctx: Context) -> DataFrame:
    return lists_single(ctx.graph.manifest)


def explain(program: BlockProgram, graph: BlockedGraph, lane: str = "both", bins: int = 4, budget_bytes: int = 1 << 20) -> DataFrame:
    """The plan of the first round as a table."""
    return plan(program, Context(graph), lane, bins, budget_bytes).orderBy(F.desc("weight"), "list_id")
