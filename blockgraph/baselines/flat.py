"""The five problems on plain edge tables, without blocks: what the blocked methods are measured against."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..algorithms.components import components_hook, components_sampled, components_spread, components_decompose, components_fast_hook  # noqa: F401  they need no blocks
from ..algorithms.triangles import many_edges
from ..operators.prepare import orient, symmetric
from ..plans import packed
from ..plans.store import stored


def pagerank(edges: DataFrame, vertices: DataFrame, damping: float = 0.85, tol: float = 1e-4, max_iter: int = 20) -> DataFrame:
    both = stored(symmetric(edges.select("src", "dst")), "edges")
    n = vertices.count()
    out = both.groupBy("src").agg(F.count("*").alias("deg"))
    ranks = vertices.select("id", F.lit(1.0 / n).alias("rank"))
    for _ in range(max_iter):
        share = ranks.join(out, F.col("id") == F.col("src")).select("src", (F.col("rank") / F.col("deg")).alias("s"))
        x = both.join(share, "src").groupBy(F.col("dst").alias("id")).agg(F.sum("s").alias("x"))
        new = stored(ranks.join(x, "id", "left").select("id", ((1 - damping) / n + damping * F.coalesce("x", F.lit(0.0))).alias("rank"), F.col("rank").alias("old")), "ranks")
        delta = new.agg(F.sum(F.abs(F.col("rank") - F.col("old")))).first()[0]
        ranks = new.select("id", "rank")
        if delta < tol:
            break
    return ranks


def bfs(edges: DataFrame, vertices: DataFrame, source: int) -> DataFrame:
    both = stored(symmetric(edges.select("src", "dst")), "edges")
    visited = vertices.where(F.col("id") == source).select("id", F.col("id").alias("parent"), F.lit(0).alias("level"))
    level = 0
    while True:
        frontier = visited.where(F.col("level") == level).select(F.col("id").alias("src"))
        new = both.join(frontier, "src").groupBy(F.col("dst").alias("id")).agg(F.min("src").alias("parent")).join(visited.select("id"), "id", "left_anti")
        new = stored(new.withColumn("level", F.lit(level + 1)), "level")
        if not new.limit(1).count():
            return visited
        visited = stored(visited.unionByName(new), "visited")
        level += 1


def triangles(edges: DataFrame) -> DataFrame:
    """Wedges of the oriented graph, closed by a join; in packed kernels where they are too many to be shuffled."""
    if many_edges(edges):
        return packed.triangle_count(edges)
    up = orient(edges)
    closed = up.join(up.withColumnRenamed("v", "w"), "u").join(up.select(F.col("u").alias("v"), F.col("v").alias("w")), ["v", "w"])
    return closed.agg(F.count("*").alias("triangles"))


def triangles_wedge(edges: DataFrame) -> DataFrame:
    """Vertex-local enumeration: all pairs of later neighbours by id, closed by a join; in packed kernels where they are too many to be shuffled."""
    if many_edges(edges):
        return packed.triangle_count(edges)
    up = edges.select(F.least("src", "dst").alias("u"), F.greatest("src", "dst").alias("v"))
    pairs = up.join(up.withColumnRenamed("v", "w"), "u").where("v < w")
    return pairs.join(up.select(F.col("u").alias("v"), F.col("v").alias("w")), ["v", "w"], "left_semi").agg(F.count("*").alias("triangles"))
