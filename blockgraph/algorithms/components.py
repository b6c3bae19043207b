"""Connected components. A component's label is its least vertex id, by every method.

All methods work on (src, dst) of an undirected graph and a vertex table (id). Links between labels shrink with every
round, so after the first hook only links between roots are moved, and vertex labels are rewritten at the end of a round.
``log`` receives (round, step, count) rows.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.bits import MULTIPLIER, PRIME, int_hash
from ..operators.exchange import gather, scatter
from ..plans import cuts as cutting
from ..plans.blocks import block_graph, placed
from ..plans.kernels import combining
from ..plans.program import Context, merge, run
from ..plans.store import Kept, bucketed, stored

JUMPS_PER_JOB = 2
ROUNDS_PER_JOB = 5
STEPS_PER_JOB = 6
#: Rounds of propagation after which what is still apart is contracted.
SPREAD_ROUNDS = 40
#: Links of a decomposition that a task takes at once.
LOCAL_LINKS = 1 << 18


def _start(vertices: DataFrame) -> DataFrame:
    return vertices.select("id", F.col("id").alias("component"))


def _lift(links: DataFrame, labels: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """Links (a, b) between the current labels of their ends, without loops and repeats."""
    x = links.join(labels.select(F.col("id").alias(a), F.col("component").alias("x")), a).join(labels.select(F.col("id").alias(b), F.col("component").alias("y")), b)
    return x.where("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()


def _compress(hooks: DataFrame, turn: int, log: list | None) -> DataFrame:
    """(root, parent) with every parent replaced by the end of its chain: pointer jumping on roots only."""
    while True:
        jumped = hooks.withColumn("first", F.col("parent"))
        for _ in range(JUMPS_PER_JOB):
            up = jumped.select(F.col("root").alias("r2"), F.col("parent").alias("p2"))
            jumped = jumped.join(up, F.col("parent") == F.col("r2"), "left").select("root", F.coalesce("p2", "parent").alias("parent"), "first")
        jumped = stored(jumped, "jumps")
        moved = jumped.where("parent <> first").count()
        if log is not None:
            log.append((turn, "link", moved))
        hooks = jumped.select("root", "parent")
        if not moved:
            return hooks


def _relabel(labels: DataFrame, hooks: DataFrame) -> DataFrame:
    return labels.join(hooks.withColumnRenamed("root", "component"), "component", "left").select("id", F.coalesce("parent", "component").alias("component"))


def _offer(ctx: Context, links: DataFrame) -> DataFrame:
    """The smaller root of every link, offered to the larger one."""
    return links.select(F.col("dst").alias("root"), F.col("src").alias("parent"))


def _hook_rounds(links: DataFrame, labels: DataFrame, log: list | None, wide: bool = False, lane: str = "light", p: int = 4) -> DataFrame:
    """Hook the larger root of every link below the least smaller one, compress, until no link is left.

    A block program: its kernels make the offers of the links in their blocks, and the step behind a round hooks, jumps and moves the
    links on to the new roots. The hook has both lanes; the jumps are a join of the roots with themselves, in SQL in every lane.
    """
    cuts = cutting.symmetric(links.withColumnsRenamed({"a": "src", "b": "dst"}), p, "uniform") if lane == "both" else None
    ctx_labels = {"labels": labels, "links": links}

    def after(ctx: Context, updates: DataFrame) -> bool:
        links, labels = ctx_labels["links"], ctx_labels["labels"]
        hooks = merge(updates, ["root"], "parent", "min")
        if wide:
            # Offer a root also what its neighbours are offered.
            other = links.select(F.col("a").alias("root"), "b").join(hooks.withColumnsRenamed({"root": "b", "parent": "p"}), "b").where("p < root").groupBy("root").agg(F.min("p").alias("parent"))
            hooks = hooks.unionByName(other).groupBy("root").agg(F.min("parent").alias("parent"))
        hooks = stored(hooks, "hooks")
        n = hooks.count()
        if log is not None:
            log.append((ctx.round, "hook", n))
        if not n:
            return False
        hooks = _compress(hooks, ctx.round, log)
        labels = stored(_relabel(labels, hooks), "labels")
        to = hooks.select(F.col("root").alias("x"), F.col("parent").alias("px"))
        moved = links.join(to, F.col("a") == F.col("x"), "left").withColumn("a", F.coalesce("px", "a")).drop("x", "px")
        moved = moved.join(to, F.col("b") == F.col("x"), "left").withColumn("b", F.coalesce("px", "b")).drop("x", "px")
        links = stored(moved.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "links")
        ctx_labels.update(labels=labels, links=links)
        ctx.graph = placed(links, cuts)
        return True

    run(combining(_offer, "min", after), placed(links, cuts), lane=lane)
    return ctx_labels["labels"]


def _links(edges: DataFrame) -> DataFrame:
    return edges.where("src <> dst").select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b"))


def components_hook(edges: DataFrame, vertices: DataFrame, log: list | None = None, lane: str = "light") -> DataFrame:
    """Hook and compress: even rounds hook roots, odd rounds jump pointers to the root."""
    return _hook_rounds(stored(_links(edges), "links"), _start(vertices), log, lane=lane)


def components_fast_hook(edges: DataFrame, vertices: DataFrame, log: list | None = None, lane: str = "light") -> DataFrame:
    """Hook and compress in which a root is also offered its neighbours' parents, which saves rounds on some graphs."""
    return _hook_rounds(stored(_links(edges), "links"), _start(vertices), log, wide=True, lane=lane)


def _spread_rounds(edges: DataFrame, vertices: DataFrame, log: list | None, turn: int, until: int, lane: str) -> tuple[DataFrame, int, bool]:
    """Rounds of propagation from number ``turn`` on: labels, the next round's number, and whether a round changed nothing.

    A vertex sends its label only after a round that changed it; before, its neighbours have it already."""
    graph = block_graph(edges.select("src", "dst"), vertices, keep=True)
    kept, found, start = Kept(), {}, turn

    def send(ctx: Context, links: DataFrame) -> DataFrame:
        k = ctx.round % ROUNDS_PER_JOB
        fresh = ctx.state.where(f"not l{k} <=> {f'l{k - 1}' if k else 'before'}")
        return gather(links, fresh.withColumnRenamed(f"l{k}", "l").hint("shuffle_hash"), "l").select(F.col("dst").alias("id"), "l")

    def after(ctx: Context, updates: DataFrame) -> bool:
        k = ctx.round % ROUNDS_PER_JOB
        joined = ctx.state.join(scatter(updates, "l", "min").hint("shuffle_hash"), "id", "left")
        ctx.state = kept.keep(joined.select(*ctx.state.columns, F.least(f"l{k}", F.coalesce("l", f"l{k}")).alias(f"l{k + 1}")))
        if k + 1 < ROUNDS_PER_JOB:
            return True
        state = stored(ctx.state, "labels")
        kept.release()
        changes = state.agg(*(F.sum((F.col(f"l{j}") != F.col(f"l{j + 1}")).cast("long")) for j in range(ROUNDS_PER_JOB))).first()
        last = F.col(f"l{ROUNDS_PER_JOB}")
        for j, n in enumerate(changes):
            done = start + ctx.round - k + j + 1
            if log is not None:
                log.append((done - 1, "spread", n or 0))
            if not n or done >= until:
                found.update(labels=state.select("id", last.alias("component")), done=done, settled=not n)
                return False
        ctx.state = state.select("id", F.col(f"l{ROUNDS_PER_JOB - 1}").alias("before"), last.alias("l0"))
        return True

    run(combining(send, "min", after, static=True), graph, vertices.select("id", F.lit(None).cast("long").alias("before"), F.col("id").alias("l0")), lane)
    return found["labels"], found["done"], found["settled"]


def components_spread(edges: DataFrame, vertices: DataFrame, log: list | None = None, max_rounds: int = 10_000, lane: str = "light") -> DataFrame:
    """Label propagation: the least label of the neighbourhood, until nothing changes. Several rounds per job.

    Where labels still move after ``SPREAD_ROUNDS`` rounds, every vertex is contracted to the end of its chain of labels, and propagation goes on
    between these. Such ends are the least of all within that many steps, so few are left of a long path."""
    found, turn, settled = _spread_rounds(edges, vertices, log, 0, min(SPREAD_ROUNDS, max_rounds), lane)
    labels, links = None, _links(edges)
    while True:
        if not settled and turn < max_rounds:
            hooks = _compress(stored(found.where("id <> component").select(F.col("id").alias("root"), F.col("component").alias("parent")), "hooks"), turn, log)
            found = stored(_relabel(found, hooks), "labels")
        labels = found if labels is None else stored(_relabel(labels, found.select(F.col("id").alias("root"), F.col("component").alias("parent"))), "labels")
        if settled or turn >= max_rounds:
            return labels
        links = stored(_lift(links, found), "links")
        if links.isEmpty():
            return labels
        nodes = stored(links.select(F.explode(F.array("a", "b")).alias("id")).distinct(), "nodes")
        found, turn, settled = _spread_rounds(links.withColumnsRenamed({"a": "src", "b": "dst"}), nodes, log, turn, min(turn + SPREAD_ROUNDS, max_rounds), lane)


def _few_neighbours(links: DataFrame, rounds: int) -> DataFrame:
    """Up to ``rounds`` links per end of every vertex: to its least larger and its greatest smaller neighbours, found by sums that
    Spark combines before the shuffle, so that a hub's neighbours are never brought together."""
    out, up, down = None, links, links
    for k in range(rounds):
        low, high = up.groupBy("a").agg(F.min("b").alias("b")), down.groupBy("b").agg(F.max("a").alias("a")).select("a", "b")
        one = low.unionByName(high)
        out = one if out is None else out.unionByName(one)
        if k + 1 < rounds:
            up = up.join(low.withColumnRenamed("b", "seen"), "a").where("b > seen").drop("seen")
            down = down.join(high.withColumnRenamed("a", "seen"), "b").where("a < seen").select("a", "b")
    return out.distinct()


def components_sampled(
    edges: DataFrame, vertices: DataFrame, neighbour_rounds: int = 1, sample: int = 1024, seed: int = 1, log: list | None = None, lane: str = "light", finish: str | None = None
) -> DataFrame:
    """Join over a few neighbours of each vertex first, find the likely giant in a sample of labels, and then move only edges
    with an end outside it. Labels never depend on the sample: an edge inside the giant joins nothing.

    The first phase runs in ``lane``, the last one in ``finish`` (the same one if absent)."""
    links = stored(_links(edges), "links")
    labels = stored(_hook_rounds(stored(_few_neighbours(links, neighbour_rounds), "links"), _start(vertices), log, lane=lane), "labels")
    drawn = labels.orderBy(int_hash(F.pmod("id", F.lit(PRIME)), seed), "id").limit(sample)
    top = drawn.groupBy("component").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "component").first()
    outside = labels.where(F.col("component") != top.component) if top is not None else labels
    outside = stored(outside.select(F.col("id").alias("v")), "outside")
    # Mostly a small table: then a broadcast one, and the links stay where they are.
    first = links.join(outside, F.col("a") == F.col("v"), "left_semi")
    second = links.join(outside, F.col("b") == F.col("v"), "left_semi")
    rest = stored(first.unionByName(second).distinct(), "rest")
    if log is not None:
        total = links.count()
        log.append((-1, "skipped", total - rest.count()))
        log.append((-1, "edges", total))
    return _hook_rounds(stored(_lift(rest, labels), "links"), labels, log, lane=finish or lane)


def _starts(ids: np.ndarray, turn: int, beta: float, seed: int) -> np.ndarray:
    """Start times as in :func:`components_decompose`."""
    x = ids.astype(np.int64) % PRIME
    for r in range(3 + turn):
        x = (x * MULTIPLIER + (seed + turn + r)) % PRIME
    return -np.floor(-np.log((x + 1) / (PRIME + 1.0)) / beta).astype(np.int64)


def _balls(beta: float, seed: int, first: int, max_rounds: int) -> Callable:
    """The turns of a decomposition from number ``first`` on, over links (a, b) that lie in one task: (id, centre) of the last balls."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [np.stack([batch.column(k).to_numpy(zero_copy_only=False) for k in range(2)]) for batch in batches if batch.num_rows]
        if not parts:
            return
        names, at = np.unique(np.concatenate(parts, 1), return_inverse=True)
        n, (a, b) = len(names), at.reshape(2, -1)
        ball, turn = np.arange(n), first
        while len(a):
            # After many turns the starts follow the ids, so that whoever has a lesser neighbour is taken.
            begin = _starts(names, turn, beta, seed) if turn < max_rounds else np.arange(n)
            # Arrival and centre in one number.
            best = (begin - begin.min()) * n + np.arange(n)
            while True:
                grown = best.copy()
                np.minimum.at(grown, a, best[b] + n)
                np.minimum.at(grown, b, best[a] + n)
                if (grown == best).all():
                    break
                best = grown
            centre = best % n
            ball, a, b = centre[ball], centre[a], centre[b]
            a, b = np.minimum(a, b)[a != b], np.maximum(a, b)[a != b]
            a, b = np.divmod(np.unique(a * n + b), n)
            turn += 1
        yield pa.RecordBatch.from_arrays([pa.array(names), pa.array(names[ball])], ["id", "centre"])

    return run


def components_decompose(edges: DataFrame, vertices: DataFrame, beta: float = 0.4, seed: int = 1, log: list | None = None, max_rounds: int = 60) -> DataFrame:
    """Low-diameter decomposition: vertices start balls at seeded, exponentially spread times, balls grow step by step over
    free vertices, are contracted, and the rest is decomposed again until no link is left. Several steps per job. Labels are turned
    to least members at the end.

    A vertex belongs to the ball that is there first, of several the one with the least centre. So balls grow by least (arrival, centre)
    from all vertices at once, which takes as many steps as the widest ball, and only vertices that were reached anew go on. Once few links
    are left, a kernel in one task makes the other turns."""
    links = stored(_links(edges).distinct(), "links")
    labels = _start(vertices)
    for turn in range(max_rounds):
        many = links.count()
        if not many:
            break
        if many <= LOCAL_LINKS:
            balls = links.coalesce(1).mapInArrow(_balls(beta, seed, turn, max_rounds), "id long, centre long")
            labels = stored(_relabel(labels, balls.withColumnsRenamed({"id": "root", "centre": "parent"})), "labels")
            if log is not None:
                log.append((turn, "rest", many))
            break
        both = bucketed(links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))), "a", "links")
        # Start time: a vertex of shift s starts at -s, if it is free then. Shifts are exponential, in whole steps.
        # Each turn multiplies by another power: ids that share a start once are not tied to do so again.
        u = (int_hash(F.pmod("id", F.lit(PRIME)), seed + turn, 3 + turn) + 1) / (PRIME + 1.0)
        begin = -F.floor(-F.log(u) / beta).cast("long")
        state = both.select(F.col("a").alias("id")).distinct().select("id", F.struct(begin.alias("at"), F.col("id").alias("centre")).alias("best"), F.lit(True).alias("fresh"))
        kept = Kept()
        while True:
            for _ in range(STEPS_PER_JOB):
                near = both.join(state.where("fresh").select(F.col("id").alias("a"), "best").hint("shuffle_hash"), "a")
                near = near.groupBy(F.col("b").alias("id")).agg(F.min(F.struct((F.col("best.at") + 1).alias("at"), F.col("best.centre").alias("centre"))).alias("near"))
                nearer = F.coalesce(F.col("near") < F.col("best"), F.lit(False))
                state = kept.keep(state.join(near.hint("shuffle_hash"), "id", "left").select("id", F.when(nearer, F.col("near")).otherwise(F.col("best")).alias("best"), nearer.alias("fresh")))
            state = stored(state, "balls")
            kept.release()
            if state.where("fresh").isEmpty():
                break
        state = state.select("id", F.col("best.centre").alias("component"))
        if log is not None:
            log.append((turn, "balls", state.select("component").distinct().count()))
        labels = stored(_relabel(labels, state.select(F.col("id").alias("root"), F.col("component").alias("parent"))), "labels")
        links = stored(_lift(links, state), "links")
    else:
        labels = _hook_rounds(links, labels, log)
    least = labels.groupBy("component").agg(F.min("id").alias("least"))
    return labels.join(least, "component").select("id", F.col("least").alias("component"))


METHODS = {"hook": components_hook, "spread": components_spread, "fast_hook": components_fast_hook, "sampled": components_sampled, "decompose": components_decompose}
