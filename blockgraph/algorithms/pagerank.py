"""PageRank and HITS as repeated sparse products over blocks.

Edges stay in their buckets; each round moves ranks only. Several rounds are planned in one job, with the rank after each of
them kept as a column, so the stopping round is the same as with a check per round at a fraction of the jobs.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.exchange import gather, scatter
from ..plans.blocks import BlockedGraph
from ..plans.kernels import combining
from ..plans.program import Context, run
from ..plans.store import Kept, bucketed, discard, stored

ROUNDS_PER_JOB = 5
UNITS = 10**15
DIRECTIONS = ("pull", "push")


def _adjacency(graph: BlockedGraph, weight: Column) -> BlockedGraph:
    """The blocks with a row for each source and block: the destinations it pushes to, at most a stripe of them."""
    rows = graph.blocks.groupBy("block_id", "src").agg(F.collect_list(F.struct("dst", weight.alias("w"))).alias("to"))
    return BlockedGraph(bucketed(rows, "src", "adjacency"), graph.manifest, graph.vertices, graph.cuts, graph.layout)


def _sender(share: Callable[[Context], DataFrame], push: bool, weighted: bool) -> Callable[[Context, DataFrame], DataFrame]:
    """What edges (pull) or adjacency rows (push) carry to their destinations: (id, x)."""

    def send(ctx: Context, edges: DataFrame) -> DataFrame:
        moved = gather(edges, share(ctx), "share")
        if push:
            moved = moved.select("share", F.explode("to").alias("e")).select(F.col("e.dst").alias("dst"), F.col("e.w").alias("w"), "share")
        return moved.select(F.col("dst").alias("id"), (F.col("share") * F.col("w") if weighted else F.col("share")).alias("x"))

    return send


def pagerank(
    graph: BlockedGraph, damping: float = 0.85, tol: float = 1e-4, max_iter: int = 20, direction: str = "pull", norm: str = "l1",
    sources: list[int] | None = None, dangling: str = "drop", weight_col: str | None = None, log: list | None = None, lane: str = "light",
) -> DataFrame:
    """(id, rank). ``log`` receives (round, delta) rows.

    ``dangling="spread"`` deals the rank of vertices without outgoing edges to all; ``sources`` personalises the restart.
    ``lane`` tells who sums up what blocks send: SQL, Arrow batches, or each a share of the blocks by weight.
    """
    if direction not in DIRECTIONS or norm not in ("l1", "linf") or dangling not in ("drop", "spread"):
        raise ValueError("unknown PageRank option")
    if weight_col:
        graph = BlockedGraph(graph.blocks.withColumn("w", F.col(weight_col).cast("double")), graph.manifest, graph.vertices, graph.cuts, graph.layout)
    out = graph.blocks.groupBy(F.col("src").alias("id")).agg((F.sum("w") if weight_col else F.count("*").cast("double")).alias("deg"))
    n = graph.vertices.count()
    if not n or max_iter < 1:
        return graph.vertices.select("id", F.lit(1.0 / max(n, 1)).alias("rank"))
    start = F.lit(1.0 / n) if sources is None else F.when(F.col("id").isin(sources), 1.0 / len(set(sources))).otherwise(0.0)
    state = stored(graph.vertices.select("id").join(out, "id", "left").select("id", "deg", start.alias("base"), F.lit(1.0 / n).alias("r0")), "ranks")
    if direction == "push":
        graph = _adjacency(graph, F.col("w") if weight_col else F.lit(1.0))
    kept, table = Kept(), [state]

    def share(ctx: Context) -> DataFrame:
        return ctx.state.where("deg > 0").select("id", (F.col(f"r{ctx.round % ROUNDS_PER_JOB}") / F.col("deg")).alias("share"))

    def after(ctx: Context, updates: DataFrame) -> bool:
        k = ctx.round % ROUNDS_PER_JOB
        got: Column = F.coalesce(F.col("x"), F.lit(0.0))
        joined = ctx.state.join(scatter(updates, "x"), "id", "left")
        if dangling == "spread":
            loose = ctx.state.where("deg is null").agg(F.coalesce(F.sum(f"r{k}"), F.lit(0.0)).alias("loose"))
            joined = joined.crossJoin(F.broadcast(loose))  # one row
            got = got + F.col("loose") / n
        ctx.state = kept.keep(joined.select(*ctx.state.columns, ((1 - damping) * F.col("base") + damping * got).alias(f"r{k + 1}")))
        if k + 1 < ROUNDS_PER_JOB and ctx.round + 1 < max_iter:
            return True
        now = stored(ctx.state, "ranks")
        kept.release()
        discard(table.pop())
        table.append(now)
        steps = [F.abs(F.col(f"r{j + 1}") - F.col(f"r{j}")) for j in range(k + 1)]
        deltas = list(now.agg(*((F.sum if norm == "l1" else F.max)(x) for x in steps)).first())
        for j, delta in enumerate(deltas):
            turn = ctx.round - k + j + 1
            if log is not None:
                log.append((turn, float(delta)))
            if delta < tol or turn == max_iter:
                ctx.globals["ranks"] = now.select("id", F.col(f"r{j + 1}").alias("rank"))
                return False
        ctx.state = now.select("id", "deg", "base", F.col(f"r{k + 1}").alias("r0"))
        return True

    program = combining(_sender(share, direction == "push", bool(weight_col)), "sum", after, static=True)
    return run(program, graph, state, lane).globals["ranks"]


def pagerank_exact(graph: BlockedGraph, rounds: int = 5, lane: str = "light") -> DataFrame:
    """(id, rank_units): a fixed number of rounds in whole units (10^15 in all), the same digits on any engine and in any lane."""
    n = graph.vertices.count()
    deg = graph.blocks.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("deg"))
    state = stored(graph.vertices.select("id").join(deg, "id", "left").withColumn("r", F.lit(UNITS // max(n, 1)).cast("long")), "units")
    base, kept = UNITS * 15 // 100 // max(n, 1), Kept()

    def after(ctx: Context, updates: DataFrame) -> bool:
        ctx.state = kept.keep(ctx.state.join(scatter(updates, "x"), "id", "left").select("id", "deg", (F.lit(base) + F.expr("(85 * coalesce(x, 0L)) div 100")).cast("long").alias("r")))
        return ctx.round + 1 < rounds

    share = lambda ctx: ctx.state.where("deg > 0").select("id", F.expr("r div deg").alias("share"))
    state = stored(run(combining(_sender(share, False, False), "sum", after, static=True), graph, state, lane).state, "units")
    kept.release()
    return state.select("id", F.col("r").alias("rank_units"))


def hits(graph: BlockedGraph, max_iter: int = 10, tol: float = 0.0) -> DataFrame:
    """(id, hub, authority): each half step is a sum over neighbours, scaled to length 1."""
    state = stored(graph.vertices.select("id", F.lit(1.0).alias("hub"), F.lit(0.0).alias("authority")), "hits")

    def half(by: str, to: str, value: str) -> DataFrame:
        x = graph.blocks.join(state.select(F.col("id").alias(by), F.col(value).alias("v")), by).groupBy(F.col(to).alias("id")).agg(F.sum("v").alias("x"))
        size = F.broadcast(x.agg(F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("size")))  # one row
        return x.crossJoin(size).select("id", F.when(F.col("size") > 0, F.col("x") / F.col("size")).otherwise(0.0).alias("x"))

    for _ in range(max_iter):
        new = half("src", "dst", "hub")
        state = stored(state.join(new, "id", "left").select("id", "hub", F.coalesce("x", F.lit(0.0)).alias("authority")), "hits")
        new = half("dst", "src", "authority")
        moved = stored(state.join(new, "id", "left").select("id", F.coalesce("x", F.lit(0.0)).alias("hub"), "authority", F.abs(F.coalesce("x", F.lit(0.0)) - F.col("hub")).alias("step")), "hits")
        state = moved.drop("step")
        if tol > 0 and (moved.agg(F.sum("step")).first()[0] or 0) < tol:
            break
    return state
