"""Joins that Spark lacks as operators: ranges, intervals and as-of."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..plans.cuts import Cuts


def range_join(df: DataFrame, cuts: Cuts, column: str) -> DataFrame:
    """``df`` plus the stripe its column falls into and the stripe's bounds; the p rows of the cuts are broadcast. Rows beyond the
    outer bounds, or without a value, are in no range and drop out."""
    spans = F.broadcast(cuts.table(df.sparkSession))
    inside = df.where((F.col(column) >= cuts.bounds[0]) & (F.col(column) < cuts.bounds[-1]))
    return inside.withColumn("stripe", cuts.stripe(column)).join(spans, "stripe")


def interval_join(left: DataFrame, right: DataFrame, key: list[str], at: str, other_at: str, seconds: int) -> DataFrame:
    """Pairs of equal key with 0 <= other_at - at <= seconds. Times are cut into buckets of that width, so a row meets two
    buckets only instead of all rows of its key."""
    bucket = lambda c: F.floor(F.unix_micros(F.col(c).cast("timestamp")) / (seconds * 1_000_000))
    a = left.withColumn("_b", F.explode(F.array(bucket(at), bucket(at) + 1)))
    b = right.withColumn("_b", bucket(other_at))
    gap = F.unix_micros(F.col(other_at).cast("timestamp")) - F.unix_micros(F.col(at).cast("timestamp"))
    return a.join(b, [*key, "_b"]).where((gap >= 0) & (gap <= seconds * 1_000_000)).drop("_b")


def asof_join(left: DataFrame, right: DataFrame, key: str, at: str, values: list[str]) -> DataFrame:
    """Every left row with the values of the latest right row of its key at or before its time (null if none).

    Both sides are laid in one order per key and the last right row is carried along; nothing is paired.
    """
    extra = [c for c in left.columns if c not in (key, at)]
    a = left.select(key, at, F.lit(1).alias("_side"), *extra, F.lit(None).cast(right.select(F.struct(*values).alias("s")).schema["s"].dataType).alias("_v"))
    b = right.select(key, at, F.lit(0).alias("_side"), *(F.lit(None).cast(left.schema[c].dataType).alias(c) for c in extra), F.struct(*values).alias("_v"))
    w = W.partitionBy(key).orderBy(at, "_side").rowsBetween(W.unboundedPreceding, 0)
    carried = a.unionByName(b).withColumn("_v", F.last("_v", ignorenulls=True).over(w))
    return carried.where("_side = 1").select(key, at, *extra, *(F.col(f"_v.{v}").alias(v) for v in values))
