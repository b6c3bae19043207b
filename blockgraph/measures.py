"""Costs and accuracy: times, speed ratios, profiles, wins, load, movement, skew, residuals; and a published table as data."""

from __future__ import annotations

import statistics
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

# Speed relative to the reference CPU system on seven graphs, by system and method. 0.00 is a failure or rounds to zero.
GRAPHS = ("twitter7", "Orkut", "sk-2005", "kmer_V1r", "eu_osm", "myciel19", "kron21")
SPEEDS = {
    ("CPU-B", "PR"): (0.83, 1.01, 1.01, 0.89, 1.03, 6.96, 0.78),
    ("CPU-B", "SV/LP"): (8.40, 1.71, 1.68, 2.29, 1.81, 1.25, 1.12),
    ("CPU-B", "CC"): (0.84, 1.56, 0.98, 0.64, 0.64, 2.94, 0.81),
    ("CPU-B", "BFS"): (0.26, 0.59, 0.46, 0.34, 2.14, 0.39, 0.18),
    ("CPU-B", "TC"): (0.69, 1.06, 0.63, 0.90, 1.21, 0.44, 0.40),
    ("CPU-C", "PR"): (0.39, 0.60, 0.99, 0.43, 0.53, 2.59, 0.72),
    ("CPU-C", "SV/LP"): (1.24, 0.70, 1.05, 0.18, 0.02, 0.58, 0.66),
    ("CPU-C", "CC"): (0.02, 0.04, 0.00, 0.02, 0.01, 0.03, 0.02),
    ("CPU-C", "BFS"): (0.61, 0.67, 0.93, 0.68, 0.16, 1.37, 0.82),
    ("CPU-C", "TC"): (0.31, 0.35, 0.12, 0.30, 0.17, 0.43, 0.69),
    ("CPU-D", "PR"): (0.75, 0.98, 0.60, 0.75, 0.65, 3.21, 0.71),
    ("CPU-D", "SV/LP"): (14.24, 1.64, 0.89, 0.30, 0.13, 7.70, 0.92),
    ("CPU-D", "CC"): (0.17, 0.21, 0.12, 0.14, 0.05, 0.27, 0.09),
    ("CPU-D", "BFS"): (0.79, 0.33, 0.77, 0.27, 0.33, 0.75, 0.30),
    ("CPU-D", "TC"): (0.38, 0.87, 0.66, 0.29, 0.16, 0.52, 0.37),
    ("GPU-E", "PR"): (0.00, 2.72, 0.00, 1.01, 1.49, 12.12, 1.62),
    ("GPU-E", "SV/LP"): (0.00, 3.67, 0.00, 2.43, 2.71, 2.65, 1.57),
    ("GPU-E", "CC"): (0.00, 0.46, 0.00, 1.16, 0.99, 0.09, 0.15),
    ("GPU-E", "BFS"): (0.00, 0.00, 0.00, 0.00, 0.00, 0.00, 0.00),
    ("GPU-E", "TC"): (1.03, 0.85, 0.90, 0.00, 0.00, 0.38, 0.65),
    ("GPU-F", "PR"): (0.00, 1.28, 0.00, 1.44, 1.34, 5.42, 0.97),
    ("GPU-F", "SV/LP"): (0.00, 1.88, 0.00, 3.18, 1.22, 3.90, 0.97),
    ("GPU-F", "CC"): (0.00, 0.24, 0.00, 1.51, 0.44, 0.14, 0.09),
    ("GPU-F", "BFS"): (4.61, 1.48, 0.00, 3.59, 0.80, 3.45, 5.73),
    ("GPU-F", "TC"): (0.00, 0.74, 0.00, 0.04, 0.02, 0.29, 0.23),
    ("REF-HYB", "PR"): (4.64, 4.67, 0.80, 0.53, 0.64, 10.76, 1.79),
    ("REF-HYB", "SV/LP"): (18.02, 5.95, 1.90, 5.73, 2.95, 7.70, 1.98),
    ("REF-HYB", "CC"): (1.25, 1.53, 2.14, 1.91, 0.96, 2.40, 0.87),
    ("REF-HYB", "BFS"): (0.16, 0.89, 0.77, 0.90, 0.33, 1.00, 0.29),
    ("REF-HYB", "TC"): (3.02, 3.01, 1.69, 1.11, 3.91, 5.39, 3.48),
}


def speed_rows() -> list[tuple[str, str, str, float]]:
    """(system, method, graph, speed), with the reference CPU-A at 1."""
    methods = dict.fromkeys(m for _, m in SPEEDS)
    rows = [("CPU-A", m, g, 1.0) for m in methods for g in GRAPHS]
    return rows + [(s, m, g, v) for (s, m), values in SPEEDS.items() for g, v in zip(GRAPHS, values, strict=True)]


def speed_table(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(speed_rows(), "system string, method string, graph string, speed double")


def order_speeds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(system, method, graph, speed) over the given tables: market segments, order priorities and nations, and the orders that a
    segment has finished. A test in which it has orders and finished none is a failure, speed 0."""
    orders = spark.read.parquet(f"{sf_dir}/orders.parquet").select("o_custkey", "o_orderpriority", "o_orderstatus")
    customer = spark.read.parquet(f"{sf_dir}/customer.parquet").select("c_custkey", "c_mktsegment", "c_nationkey")
    named = orders.join(customer, F.col("c_custkey") == F.col("o_custkey")).select(F.col("c_mktsegment").alias("system"), F.col("o_orderpriority").alias("method"), F.col("c_nationkey").cast("string").alias("graph"), "o_orderstatus")
    return named.groupBy("system", "method", "graph").agg(F.count(F.when(F.col("o_orderstatus") == "F", 1)).cast("double").alias("speed"))


def median_runs(fn, n: int = 10, warmup: int = 1) -> float:
    """Median seconds of ``fn()`` after warming up; a returned DataFrame is materialised into the noop sink."""
    times = []
    for i in range(n + warmup):
        began = time.perf_counter()
        out = fn()
        if isinstance(out, DataFrame):
            out.write.format("noop").mode("overwrite").save()
        if i >= warmup:
            times.append(time.perf_counter() - began)
    return statistics.median(times)


def speedup(times: DataFrame, reference: str) -> DataFrame:
    """(system, method, graph, speed) from seconds: the reference's time over a system's; null seconds are failures, speed 0."""
    ref = times.where(F.col("system") == reference).select("method", "graph", F.col("seconds").alias("ref"))
    ratio = F.coalesce(F.col("ref") / F.col("seconds"), F.lit(0.0))
    return times.join(ref, ["method", "graph"]).select("system", "method", "graph", ratio.alias("speed"))


def speed_class(speed):
    """slower, same or faster than the reference."""
    return F.when(speed < 1, "slower").when(speed == 1, "same").otherwise("faster")


def ratios(speeds: DataFrame) -> DataFrame:
    """Adds ``ratio``: best speed of the test over the system's; null for failures."""
    best = F.max("speed").over(W.partitionBy("method", "graph"))
    return speeds.withColumn("ratio", F.when(F.col("speed") > 0, best / F.col("speed")))


def profile(speeds: DataFrame, taus=(1.0, 1.5, 2.0, 4.0, 8.0)) -> DataFrame:
    """(system, tau, tests): tests in which the system is within a factor tau of the best."""
    taus = speeds.sparkSession.createDataFrame([(float(t),) for t in taus], "tau double")
    return ratios(speeds).crossJoin(F.broadcast(taus)).groupBy("system", "tau").agg(F.sum((F.col("ratio") <= F.col("tau")).cast("long")).alias("n")).select("system", "tau", F.coalesce("n", F.lit(0)).alias("tests"))


def wins(speeds: DataFrame) -> DataFrame:
    """(system, wins, tests); ties count for all."""
    return ratios(speeds).groupBy("system").agg(F.coalesce(F.sum((F.col("ratio") == 1).cast("long")), F.lit(0)).alias("wins"), F.count("*").alias("tests"))


def median_over(speeds: DataFrame, system: str) -> DataFrame:
    """(other, median, tests): median of the system's speed over another's, on the other's non-zero tests."""
    mine = speeds.where(F.col("system") == system).select("method", "graph", F.col("speed").alias("mine"))
    rest = speeds.where((F.col("system") != system) & (F.col("speed") > 0)).join(mine, ["method", "graph"])
    return rest.groupBy(F.col("system").alias("other")).agg(F.median(F.col("mine") / F.col("speed")).alias("median"), F.count("*").alias("tests"))


def rank(speeds: DataFrame) -> DataFrame:
    """(system, wins, place), most wins first."""
    return wins(speeds).select("system", "wins", F.rank().over(W.orderBy(F.desc("wins"))).cast("long").alias("place"))


def imbalance(manifest: DataFrame, column: str = "n_edges") -> DataFrame:
    """One row: largest and mean load of a block, and their ratio."""
    return manifest.agg(F.max(column).alias("largest"), F.avg(column).alias("mean"), (F.max(column) / F.avg(column)).alias("imbalance"))


def movement(manifest: DataFrame, n_vertices: int, row_bytes: int = 16) -> DataFrame:
    """One row: attribute rows that a full round moves, per vertex, and their bytes."""
    moved = F.sum(F.col("n_src") + F.col("n_dst"))
    return manifest.agg(moved.alias("attribute_rows"), (moved / n_vertices).alias("replication"), (moved * row_bytes).alias("bytes"))


def max_list_bytes(lists: DataFrame, manifest: DataFrame) -> int:
    """Bytes of the largest list: the bound of what a task holds."""
    from .plans.planner import weigh

    return int(weigh(lists, manifest).agg(F.max("bytes")).first()[0] or 0)


def degree_skew(degrees: DataFrame) -> DataFrame:
    """One row: vertices, greatest degree, share of vertices with fewer than two neighbours, greatest over mean."""
    return degrees.agg(
        F.count("*").alias("vertices"), F.max("degree").alias("max_degree"), F.avg((F.col("degree") < 2).cast("double")).alias("low_share"), (F.max("degree") / F.avg("degree")).alias("skew")
    )


def residual(a: DataFrame, b: DataFrame, column: str = "rank") -> float:
    """L1 distance of two rank tables."""
    d = a.select("id", F.col(column).alias("x")).join(b.select("id", F.col(column).alias("y")), "id", "full_outer")
    return float(d.agg(F.sum(F.abs(F.coalesce("x", F.lit(0.0)) - F.coalesce("y", F.lit(0.0))))).first()[0] or 0.0)


def round_log(spark: SparkSession, log: list) -> DataFrame:
    """(round, step, value) of what an algorithm wrote to its log."""
    return spark.createDataFrame([(int(r), str(s), float(v)) for r, s, v in log], "round int, step string, value double")
