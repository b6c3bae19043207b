"""Synthetic graphs: Mycielski graphs and Kronecker graphs, from ``spark.range`` and whole-number hashes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.bits import PRIME, int_hash
from .operators.prepare import canonical, symmetric
from .plans.store import stored

#: Shares of the quadrants of a Kronecker step, in percent.
QUADRANTS = (57, 19, 19, 5)


def mycielski(spark: SparkSession, k: int) -> DataFrame:
    """(src, dst) of the graph of step k >= 2: a step keeps the edges, ties a copy of each vertex to its neighbours, and all copies to a new vertex."""
    if k < 2:
        raise ValueError("k must be 2 or more")
    edges, n = spark.createDataFrame([(0, 1)], "src long, dst long"), 2
    for step in range(k - 2):
        copies = symmetric(edges).select("src", (F.col("dst") + n).alias("dst"))
        top = spark.range(n).select((F.col("id") + n).alias("src"), F.lit(2 * n).cast("long").alias("dst"))
        edges, n = edges.unionByName(copies).unionByName(top), 2 * n + 1
        if step % 4 == 3:
            edges = stored(edges, "mycielski")
    return edges


def kronecker(spark: SparkSession, scale: int, edge_factor: int = 16, seed: int = 1) -> DataFrame:
    """(src, dst) over 2^scale ids: every edge picks a quadrant per level by a hash; loops and repeats are dropped."""
    return kronecker_of(spark.range(edge_factor << scale), "id", scale, seed)


def kronecker_of(rows: DataFrame, number: str, scale: int, seed: int = 1) -> DataFrame:
    """(src, dst) over 2^scale ids, an edge for every row of a table: its number takes the place of the edge's."""
    a, b, c, _ = QUADRANTS
    # Neighbouring edges get unlike hashes only after mixing with the level. As one array: a column per level makes code too long to compile.
    levels = F.transform(F.array(*(F.lit(k).cast("long") for k in range(scale))), lambda k: F.pmod(int_hash(F.pmod(F.col(number) * 2654435 + k * 97, F.lit(PRIME)), seed + 7 * k, 3), F.lit(100)))
    number_of = lambda bit: F.aggregate("h", F.lit(0).cast("long"), lambda x, h: 2 * x + bit(h).cast("long"))
    e = rows.select(levels.alias("h"))
    return canonical(e.select(number_of(lambda h: h >= a + b).alias("src"), number_of(lambda h: ((h >= a) & (h < a + b)) | (h >= a + b + c)).alias("dst")))
