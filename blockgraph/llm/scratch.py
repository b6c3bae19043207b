"""Intermediate tables in the folder that the whole cluster shares.

Iterative operators cut their lineage by writing Parquet under ``spark.checkpoint.dir`` and reading it
again, so a lost executor never costs more than the stage at hand.
"""

from __future__ import annotations

import pickle
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

LOCAL_FALLBACK = "file:///tmp/checkpoints"


def scratch_root(spark: SparkSession) -> str:
    """The shared folder; a local one only where the setting is absent and the master is local."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    return LOCAL_FALLBACK


def scratch_path(spark: SparkSession, name: str) -> str:
    return f"{scratch_root(spark)}/blockgraph-{name}-{uuid.uuid4().hex}"


def stored(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to a fresh scratch table and read it back."""
    spark = df.sparkSession
    path = scratch_path(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def discard(df: DataFrame) -> None:
    """Delete the files behind a table made by :func:`stored`; no plan may read it afterwards."""
    spark = df.sparkSession
    for path in {f.rpartition("/")[0] for f in df.inputFiles()}:
        target = spark._jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)


def small_batches(spark: SparkSession, most: int = 6 << 20) -> None:
    """Keep the batches that go to Python workers at a few MB, whatever the length of the texts.

    A running session may change this limit; it is only ever lowered.
    """
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    now = str(spark.conf.get(key, "67108864")).lower().rstrip("b")
    if not now.isdigit() or int(now) > most:
        spark.conf.set(key, str(most))


def trained(rows: DataFrame, train: Callable[[Iterator[tuple]], object]):
    """What ``train`` makes of the rows (a sample of bounded size), in one task: the driver gets the model, never the rows."""
    names = rows.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        given = (row for batch in batches for row in zip(*(batch.column(c).to_pylist() for c in names), strict=True))
        yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(train(given))], pa.binary())], ["model"])

    found = rows.coalesce(1).mapInArrow(run, "model binary").collect()
    return pickle.loads(found[0].model) if found else train(iter(()))
