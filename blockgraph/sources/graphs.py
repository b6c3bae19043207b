"""The graph suite: eight undirected graphs over the given tables, without loops or repeated edges.

Edges are (src, dst[, w]) with src < dst. Several kinds of vertices share one id space by arithmetic.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations_with_replacement

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..operators.prepare import canonical, global_rank
from ..plans.store import fresh_path, side_by_side, stored

COSINE = 0.3
#: Vectors of a block, at least and at most; rows multiplied at a time; pairs of blocks planned in one job.
BLOCK_VECTORS = 1024
MOST_VECTORS = 1 << 15
ROWS_AT_A_TIME = 256
PAIRS_PER_JOB = 256


def _read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def copurchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts in one order."""
    # Lines are dealt by their order once, for the distinct lines and for the join.
    lines = _read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").repartition("l_orderkey").distinct()
    other = lines.withColumnRenamed("l_partkey", "dst")
    return lines.join(other, "l_orderkey").where("l_partkey < dst").select(F.col("l_partkey").alias("src"), "dst").distinct()


def part_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts (even) and their suppliers (odd), weighted by quantity."""
    lines = _read(spark, sf_dir, "lineitem").select((2 * F.col("l_partkey")).alias("p"), (2 * F.col("l_suppkey") + 1).alias("s"), "l_quantity")
    both = lines.select(F.least("p", "s").alias("src"), F.greatest("p", "s").alias("dst"), "l_quantity")
    return both.groupBy("src", "dst").agg(F.sum("l_quantity").alias("w"))


def page_link(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages (even) and the targets of their links (odd, numbered in binary order)."""
    links = _read(spark, sf_dir, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("link")).distinct()
    numbered = global_rank(links.select("link").distinct(), ["link"], "n")
    return canonical(links.join(numbered, "link").select((2 * F.col("page_id")).alias("src"), (2 * F.col("n") + 1).alias("dst")))


def _chain(df: DataFrame, key: str, order: list[str], node: str) -> DataFrame:
    after = F.lead(node).over(W.partitionBy(key).orderBy(*order))
    return canonical(df.select(F.col(node).alias("src"), after.alias("dst")).where("dst is not null"))


def order_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Consecutive orders of a customer."""
    return _chain(_read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate"), "o_custkey", ["o_orderdate", "o_orderkey"], "o_orderkey")


def event_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Consecutive events of a user."""
    return _chain(_read(spark, sf_dir, "events").select("event_id", "user_id", "ts"), "user_id", ["ts", "event_id"], "event_id")


def geo_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders, customers, nations and regions: ids 4x to 4x+3."""
    orders, customer, nation = (_read(spark, sf_dir, t) for t in ("orders", "customer", "nation"))
    parts = [
        orders.select((4 * F.col("o_orderkey")).alias("src"), (4 * F.col("o_custkey") + 1).alias("dst")),
        customer.select((4 * F.col("c_custkey") + 1).alias("src"), (4 * F.col("c_nationkey").cast("long") + 2).alias("dst")),
        nation.select((4 * F.col("n_nationkey").cast("long") + 2).alias("src"), (4 * F.col("n_regionkey").cast("long") + 3).alias("dst")),
    ]
    return canonical(parts[0].unionByName(parts[1]).unionByName(parts[2]))


def _cosine_blocks(low: int, high: int, least: float):
    """Pairs of two blocks of vectors, or within one: some rows of one are multiplied with the other at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, x = {low: [], high: []}, {low: [], high: []}
        for batch in batches:
            side = batch.column("block").to_numpy(zero_copy_only=False)
            own = batch.column("vec_id").to_numpy(zero_copy_only=False)
            v = np.stack(batch.column("v").to_numpy(zero_copy_only=False)).astype(np.float64) if batch.num_rows else None
            for k in set(side.tolist()):
                ids[k].append(own[side == k])
                x[k].append(v[side == k])
        if not ids[low] or not ids[high]:
            return
        ids, x = ({k: np.concatenate(parts) for k, parts in held.items()} for held in (ids, x))
        x = {k: v / np.linalg.norm(v, axis=1, keepdims=True) for k, v in x.items()}
        repeated = any(len(np.unique(i)) < len(i) for i in ids.values())
        found = []
        for first in range(0, len(ids[low]), ROWS_AT_A_TIME):
            r, c = np.nonzero(x[low][first : first + ROWS_AT_A_TIME] @ x[high].T >= least)
            left, right = ids[low][first + r], ids[high][c]
            keep = left < right if low == high else left != right
            pairs = np.minimum(left, right)[keep], np.maximum(left, right)[keep]
            if repeated:
                found.append(np.stack(pairs, 1))
            else:
                yield pa.RecordBatch.from_arrays([pa.array(e, pa.int64()) for e in pairs], ["src", "dst"])
        if found:
            # The rows of an id are in one block, so its pairs with another id are in one task.
            yield pa.RecordBatch.from_arrays([pa.array(e, pa.int64()) for e in np.unique(np.concatenate(found), axis=0).T], ["src", "dst"])

    return run


def embed_cos(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vectors with a cosine of 0.3 or more. Vectors are dealt into blocks and stored once; a task reads two blocks and multiplies them.
    Blocks grow with the table up to a bound, so that few are read often."""
    vectors = _read(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").alias("v")).where("v is not null")
    many = vectors.count()
    n = max(1, -(-many // min(max(-(-many // 8), BLOCK_VECTORS), MOST_VECTORS)))
    path = fresh_path(spark, "vectors")
    dealt = vectors.withColumn("block", F.pmod("vec_id", F.lit(n)).cast("int"))
    dealt.repartition(n, "block").withColumn("part", F.col("block")).write.partitionBy("part").parquet(path)
    here = sorted(r.block for r in spark.read.schema("block int").parquet(path).distinct().collect())
    out = spark.createDataFrame([], "src long, dst long")
    read = lambda *blocks: spark.read.schema(dealt.schema).parquet(*(f"{path}/part={k}" for k in sorted(set(blocks))))
    pairs = list(combinations_with_replacement(here, 2))
    for first in range(0, len(pairs), PAIRS_PER_JOB):
        job = side_by_side([read(i, j).coalesce(1).mapInArrow(_cosine_blocks(i, j, COSINE), "src long, dst long") for i, j in pairs[first : first + PAIRS_PER_JOB]])
        out = out.unionAll(job if first + PAIRS_PER_JOB >= len(pairs) else stored(job, "near"))
    return out


def doc_line(spark: SparkSession, sf_dir: str, pairs_up_to: int = 50) -> DataFrame:
    """Documents that share a line of 40 characters or more: every pair of them, or, where more than ``pairs_up_to`` documents hold
    the line, each with the least of them. So no two documents that share a line are apart, and edges grow with the holders."""
    lines = _read(spark, sf_dir, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.trim("line").alias("line"))
    hashed = lines.where(F.length("line") >= 40).select("doc_id", F.md5("line").alias("h")).distinct()
    # A table of its own, so that the join can split the partition of a line that many documents hold.
    held = stored(hashed.groupBy("h").agg(F.count("*").alias("n"), F.min("doc_id").alias("least")).where("n > 1"), "lines")
    few = hashed.join(held.where(F.col("n") <= pairs_up_to), "h").select("h", "doc_id")
    pairs = few.join(few.withColumnRenamed("doc_id", "dst"), "h").where("doc_id < dst").select(F.col("doc_id").alias("src"), "dst")
    stars = hashed.join(held.where(F.col("n") > pairs_up_to), "h").where("doc_id > least").select(F.col("least").alias("src"), F.col("doc_id").alias("dst"))
    return pairs.unionByName(stars).distinct()


EDGES = {
    "copurchase": copurchase, "part_supplier": part_supplier, "page_link": page_link, "order_chain": order_chain,
    "event_chain": event_chain, "geo_tree": geo_tree, "embed_cos": embed_cos, "doc_line": doc_line,
}


def edges(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(src, dst) of a graph of the suite."""
    if name not in EDGES:
        raise ValueError(f"unknown graph {name!r}")
    return EDGES[name](spark, sf_dir).select("src", "dst")


def vertices(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """All vertices, with isolated ones where a table lists them."""
    table, column = {
        "copurchase": ("part", "p_partkey"), "order_chain": ("orders", "o_orderkey"), "event_chain": ("events", "event_id"),
        "doc_line": ("documents", "doc_id"), "embed_cos": ("embeddings", "vec_id"),
    }.get(name, (None, None))
    if table:
        return _read(spark, sf_dir, table).select(F.col(column).alias("id"))
    e = edges(spark, sf_dir, name)
    return e.select(F.col("src").alias("id")).unionByName(e.select(F.col("dst").alias("id"))).distinct()
