"""Sinks of streams: Parquet folders written once a micro-batch, whatever is retried."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame

from ..sources.storage import new_path


def save_batch(path: str, *partition_by: str) -> Callable[[DataFrame, int], None]:
    """A foreachBatch function: each micro-batch has a folder of its own, which a repeat overwrites."""

    def save(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").partitionBy(*partition_by).parquet(f"{path}/batch_id={batch_id}")

    return save


def drain(stream: DataFrame, path: str, checkpoint: str, mode: str = "append", partition_by: tuple = ()) -> dict:
    """Run a stream to the end of its input into path; its last progress report.

    A second run with the same checkpoint takes only what is new.
    """
    q = stream.writeStream.foreachBatch(save_batch(path, *partition_by)).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return q.lastProgress or {}


def saved(spark, path: str, schema, last_only: bool = False) -> DataFrame:
    """What drain has written; last_only: the last micro-batch, which in complete mode is the whole result."""
    jvm = spark.sparkContext._jvm
    root = jvm.org.apache.hadoop.fs.Path(path)
    fs = root.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf())
    ids = sorted(int(s.getPath().getName().split("=")[1]) for s in fs.listStatus(root)) if fs.exists(root) else []
    if not ids:
        return spark.createDataFrame([], schema)
    if last_only:
        return spark.read.schema(schema).parquet(f"{path}/batch_id={ids[-1]}")
    return spark.read.schema(schema).parquet(*(f"{path}/batch_id={i}" for i in ids))


def run_once(stream: DataFrame, mode: str) -> DataFrame:
    """Run a stream to the end of its input and return its result table, from the shared folder."""
    spark = stream.sparkSession
    path = new_path(spark, "stream")
    drain(stream, f"{path}/out", f"{path}/checkpoint", mode)
    return saved(spark, f"{path}/out", stream.schema, last_only=mode == "complete")
