"""Cleaning and ordering of edge tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..plans.store import stored


def canonical(edges: DataFrame) -> DataFrame:
    """No loops, one row per unordered pair, src < dst."""
    pairs = edges.where("src <> dst").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"))
    return pairs.distinct()


def symmetric(edges: DataFrame) -> DataFrame:
    """Both directions of every edge; other columns go along."""
    rest = [c for c in edges.columns if c not in ("src", "dst")]
    return edges.select("src", "dst", *rest).unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *rest))


def endpoints(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("src", "dst")).alias("id")).distinct()


def degrees(edges: DataFrame, vertices: DataFrame | None = None) -> DataFrame:
    """(id, degree); vertices without an edge have 0 if a vertex table is given."""
    counted = edges.select(F.explode(F.array("src", "dst")).alias("id")).groupBy("id").agg(F.count("*").alias("degree"))
    if vertices is None:
        return counted
    return vertices.join(counted, "id", "left").select("id", F.coalesce("degree", F.lit(0)).cast("long").alias("degree"))


def global_rank(df: DataFrame, order: list[str], name: str, parts: int | None = None) -> DataFrame:
    """``df`` plus its place (from 0) in the order of the columns, without a window over everything.

    Rows are range partitioned and stored with their partition number; counts of the partitions give offsets.
    """
    parts = parts or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = stored(df.repartitionByRange(parts, *order).withColumn("_part", F.spark_partition_id()), "ranges")
    counts = dealt.groupBy("_part").agg(F.count("*").alias("_n"))
    # One row per partition.
    offsets = counts.select("_part", (F.sum("_n").over(W.orderBy("_part")) - F.col("_n")).alias("_before"))
    place = F.row_number().over(W.partitionBy("_part").orderBy(*order)) - 1
    return dealt.join(F.broadcast(offsets), "_part").withColumn(name, F.col("_before") + place).drop("_part", "_before")


def degree_rank(edges: DataFrame) -> DataFrame:
    """(id, rank): ids renumbered from 0 by (degree, id)."""
    return global_rank(degrees(edges), ["degree", "id"], "rank").select("id", "rank")


def orient(edges: DataFrame, order: str = "degree") -> DataFrame:
    """Every edge once, from the lower to the higher end by (degree, id) or by id: (u, v)."""
    if order == "id":
        return edges.select(F.least("src", "dst").alias("u"), F.greatest("src", "dst").alias("v"))
    if order != "degree":
        raise ValueError(f"unknown order {order!r}")
    d = degrees(edges)
    e = edges.join(d.select(F.col("id").alias("src"), F.col("degree").alias("ds")), "src").join(d.select(F.col("id").alias("dst"), F.col("degree").alias("dd")), "dst")
    first = (F.col("ds") < F.col("dd")) | ((F.col("ds") == F.col("dd")) & (F.col("src") < F.col("dst")))
    return e.select(F.when(first, F.col("src")).otherwise(F.col("dst")).alias("u"), F.when(first, F.col("dst")).otherwise(F.col("src")).alias("v"))


def ranked_edges(edges: DataFrame) -> DataFrame:
    """Edges between degree ranks, src < dst: the oriented graph with dense ids."""
    return between_ranks(edges, stored(degree_rank(edges), "ranks"))


def between_ranks(edges: DataFrame, ranks: DataFrame) -> DataFrame:
    """Edges between the ranks (id, rank) of their ends, src < dst."""
    e = edges.join(ranks.withColumnsRenamed({"id": "src", "rank": "a"}), "src").join(ranks.withColumnsRenamed({"id": "dst", "rank": "b"}), "dst")
    return e.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"))


def largest(labels: DataFrame) -> DataFrame:
    """The vertices (id) of the component with most of them (least label among equals)."""
    top = labels.groupBy("component").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "component").limit(1).select("component")
    return labels.join(F.broadcast(top), "component", "left_semi").select("id")


def largest_component(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """The edges of the component with most vertices (least label among equals)."""
    return edges.join(largest(labels).select(F.col("id").alias("src")), "src", "left_semi")


def reorder_by_level(edges: DataFrame, levels: DataFrame) -> DataFrame:
    """Edges between new ids that follow (level, id) of a traversal; unreached vertices drop out."""
    place = stored(global_rank(levels.select("level", "id"), ["level", "id"], "rank").select("id", "rank"), "levels")
    e = edges.join(place.withColumnsRenamed({"id": "src", "rank": "a"}), "src").join(place.withColumnsRenamed({"id": "dst", "rank": "b"}), "dst")
    return e.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"))
