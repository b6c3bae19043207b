"""Streams of edges from the events table: windows, late data, repeats, state, joins, and components kept up to date.

Each function starts a query over files with an available-now trigger, waits for it, and returns the result as a table, so
that a replay can be held against the batch answer.
"""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..algorithms.components import components_hook
from ..plans.store import fresh_path, stored

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def edge_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """(event_id, at, user_id, item, event_type): a user and the item in the event's properties. ``at`` is a timestamp, as watermarks need."""
    events = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return _edges(events)


def _edges(events: DataFrame) -> DataFrame:
    return events.select("event_id", F.col("ts").cast("timestamp").alias("at"), "user_id", F.get_json_object("props", "$.k").cast("long").alias("item"), "event_type", "value")


def batch_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _edges(spark.read.parquet(f"{sf_dir}/events.parquet"))


def source_folder(spark: SparkSession, sf_dir: str, parts: int = 1, reverse: bool = False) -> str:
    """The events in files by time, for replays in several triggers.

    A file stream takes files by their time of writing, so they are written one after another: oldest events first, or last."""
    path = fresh_path(spark, "events")
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    dealt = stored(events.repartitionByRange(parts, "ts").withColumn("part", F.spark_partition_id()), "events-dealt")
    for k in sorted(range(parts), reverse=reverse):
        dealt.where(F.col("part") == k).drop("part").coalesce(1).sortWithinPartitions("ts", "event_id").write.mode("append").parquet(path)
    return path


def replay(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a query over what is there and return its rows. Results go to files in the shared folder (or memory for complete output)."""
    spark = stream.sparkSession
    if mode == "append":
        out = fresh_path(spark, "stream-out")
        query = stream.writeStream.outputMode(mode).format("parquet").option("checkpointLocation", fresh_path(spark, "stream")).trigger(availableNow=True).start(out)
        query.awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)
    name = f"replay_{uuid.uuid4().hex}"
    query = stream.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", fresh_path(spark, "stream")).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.table(name)


def tumbling(edges: DataFrame, size: str = "1 day") -> DataFrame:
    w = F.window("at", size)
    return edges.groupBy(w.alias("w")).agg(F.count("*").alias("edges"), F.approx_count_distinct("user_id").alias("users")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "edges")


def sliding(edges: DataFrame, size: str = "2 days", slide: str = "1 day") -> DataFrame:
    return edges.groupBy(F.window("at", size, slide).alias("w")).agg(F.count("*").alias("edges")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "edges")


def sessions(edges: DataFrame, gap: str = "12 hours") -> DataFrame:
    """(user_id, start, edges) of stretches of a user's events without a pause of ``gap``."""
    g = edges.groupBy("user_id", F.session_window("at", gap).alias("w")).agg(F.count("*").alias("edges"))
    return g.select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "edges")


def _degree_state(key, batches, state):
    """Running number of edges of a user."""
    n = state.get[0] if state.exists else 0
    for pdf in batches:
        n += len(pdf)
    state.update((n,))
    yield pd.DataFrame({"user_id": [key[0]], "degree": [n]})


def degrees_with_state(edges: DataFrame) -> DataFrame:
    """(user_id, degree) after every trigger that touched the user."""
    return edges.groupBy("user_id").applyInPandasWithState(_degree_state, "user_id long, degree long", "n long", "update", "NoTimeout")


def latest_degrees(spark: SparkSession, path: str) -> DataFrame:
    out = fresh_path(spark, "degrees")
    query = (
        degrees_with_state(edge_stream(spark, path)).writeStream.outputMode("update").option("checkpointLocation", fresh_path(spark, "stream"))
        .foreachBatch(lambda df, n: df.withColumn("batch", F.lit(n)).write.mode("append").parquet(out)).trigger(availableNow=True).start()
    )
    query.awaitTermination()
    return spark.read.parquet(out).groupBy("user_id").agg(F.max_by("degree", "batch").alias("degree"))


def dedup(edges: DataFrame, delay: str = "1 hour") -> DataFrame:
    return edges.withWatermark("at", delay).dropDuplicatesWithinWatermark(["event_id"])


def late_drop(edges: DataFrame, delay: str = "1 hour", size: str = "1 hour") -> DataFrame:
    """Counts per window; edges that come later than the delay no longer count."""
    return edges.withWatermark("at", delay).groupBy(F.window("at", size).alias("w")).agg(F.count("*").alias("edges")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "edges")


def with_static(edges: DataFrame, vertices: DataFrame, key: str) -> DataFrame:
    return edges.join(vertices, key)


def purchases_after_clicks(edges: DataFrame, within: str = "1 hour") -> DataFrame:
    """(user_id, click, purchase): purchases up to an hour after a click of the same user. On streams both sides carry a watermark."""
    if edges.isStreaming:
        edges = edges.withWatermark("at", within)
    c = edges.where("event_type = 'click'").select(F.col("user_id").alias("u"), F.col("event_id").alias("click"), F.col("at").alias("click_at"))
    p = edges.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase"), F.col("at").alias("purchase_at"))
    near = F.expr(f"user_id = u and purchase_at >= click_at and purchase_at <= click_at + interval {within}")
    return c.join(p, near).select("user_id", "click", "purchase")


class IncrementalComponents:
    """Component labels under arriving edges: new links are lifted to the roots they touch, joined there, and merged into the label table."""

    def __init__(self, spark: SparkSession):
        self.labels = stored(spark.createDataFrame([], "id long, component long"), "labels")

    def add(self, edges: DataFrame) -> None:
        edges = stored(edges.select("src", "dst"), "new-edges")
        seen = edges.select(F.explode(F.array("src", "dst")).alias("id")).distinct()
        labels = self.labels.unionByName(seen.join(self.labels, "id", "left_anti").select("id", F.col("id").alias("component")))
        at = labels.join(seen, "id", "left_semi")
        roots = edges.join(at.select(F.col("id").alias("src"), F.col("component").alias("a")), "src").join(at.select(F.col("id").alias("dst"), F.col("component").alias("b")), "dst")
        roots = stored(roots.where("a <> b").select(F.col("a").alias("src"), F.col("b").alias("dst")).distinct(), "roots")
        touched = roots.select(F.explode(F.array("src", "dst")).alias("id")).distinct()
        joined = components_hook(roots, touched).select(F.col("id").alias("component"), F.col("component").alias("least"))
        self.labels = stored(labels.join(joined, "component", "left").select("id", F.coalesce("least", "component").alias("component")), "labels")


def stream_components(spark: SparkSession, path: str) -> DataFrame:
    """(id, component) of the graph user (even) - item (odd), kept up to date trigger by trigger."""
    kept = IncrementalComponents(spark)
    links = edge_stream(spark, path).select((2 * F.col("user_id")).alias("src"), (2 * F.col("item") + 1).alias("dst"))
    links.writeStream.foreachBatch(lambda df, n: kept.add(df)).option("checkpointLocation", fresh_path(spark, "stream")).trigger(availableNow=True).start().awaitTermination()
    return kept.labels
