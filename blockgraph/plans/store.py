"""Rounds kept as tables in the folder the cluster shares, so that plans stay short and losses stay cheap."""

from __future__ import annotations

import uuid
from functools import reduce

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession

LOCAL_FALLBACK = "file:///tmp/checkpoints"


def shared_folder(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; a local folder only where it is unset and the master is local."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    return LOCAL_FALLBACK


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_folder(spark)}/blockgraph-{name}-{uuid.uuid4().hex}"


def stored(df: DataFrame, name: str = "round") -> DataFrame:
    """Write ``df`` to a fresh table and read it back."""
    path = fresh_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def bucketed(df: DataFrame, key: str, name: str = "blocks", order: list[str] | None = None) -> DataFrame:
    """Write ``df`` in buckets of ``key``, sorted, and read it as a table: a join on the key moves only the other side.

    There are as many buckets as shuffle partitions, so the session's setting for the scale holds here too.
    """
    spark = df.sparkSession
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    table = f"blockgraph_{name}_{uuid.uuid4().hex}"
    df.repartition(n, key).write.format("parquet").bucketBy(n, key).sortBy(*(order or [key])).option("path", fresh_path(spark, name)).saveAsTable(table)
    return spark.table(table)


def side_by_side(frames: list[DataFrame]) -> DataFrame:
    """The rows of frames of one partition each, a task for every frame.

    A union of single partitions alone is laid out as a single partition again, so that one task would do the work of all. An empty
    frame of two partitions keeps them apart.
    """
    schema = frames[0].schema
    apart = frames[0].sparkSession.range(0, 2, 1, 2).mapInArrow(lambda batches: (b for batch in batches for b in ()), schema)
    return reduce(DataFrame.unionAll, frames, apart)


def drop(spark: SparkSession, path: str) -> None:
    """Delete a stored folder; no plan may read it afterwards."""
    target = spark._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)


def discard(df: DataFrame) -> None:
    """Delete the files of a table made by :func:`stored`; no plan may read it afterwards."""
    for path in {f.rpartition("/")[0] for f in df.inputFiles()}:
        drop(df.sparkSession, path)


class Kept:
    """Intermediate rounds held in memory (or on disk) between two stored tables, so that each is computed once and
    plans refer to it by name. What a lost executor held is computed again from the last stored table."""

    def __init__(self):
        self.held: list[DataFrame] = []

    def keep(self, df: DataFrame) -> DataFrame:
        self.held.append(df.persist(StorageLevel.MEMORY_AND_DISK))
        return self.held[-1]

    def release(self) -> None:
        for df in self.held:
            df.unpersist()
        self.held.clear()
