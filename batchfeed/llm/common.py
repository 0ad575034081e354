"""Reading, shared storage and word helpers used by the operators.

Words of `[^\\x20\\x09-\\x0D]+` are what `bytes.split()` returns for UTF-8, since
it cuts at exactly those six bytes; `bytes.lower()` changes A-Z alone.
"""

from __future__ import annotations

import contextlib
import gc
import time
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, functions as F

ASCII_SPACE = " \t\n\x0b\x0c\r"


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """The named columns of an input table, read by Spark."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def shared_dir(spark: SparkSession) -> str:
    """A folder that the driver and all executors see.

    `spark.checkpoint.dir` where it is set, else the context's checkpoint folder,
    else a folder in the warehouse.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        base = found.get() if found.isDefined() else spark.conf.get("spark.sql.warehouse.dir") + "/_shared"
    return base.rstrip("/")


_MADE: list[str] = []


def new_path(spark: SparkSession, label: str) -> str:
    """A fresh path in the shared folder; `scratch` removes what was made inside it."""
    path = f"{shared_dir(spark)}/batchfeed-{label}-{uuid.uuid4().hex}"
    _MADE.append(path)
    return path


@contextlib.contextmanager
def scratch(spark: SparkSession):
    """Remove, at its end, the folders that operators made inside, but for those that `keep` names.

    For callers that have written an operator's result; yields keep(path).
    """
    first, kept = len(_MADE), set()
    try:
        yield kept.add
    finally:
        mine = [p for p in _MADE[first:] if p not in kept]
        del _MADE[first:]
        remove(spark, *mine)


def remove(spark: SparkSession, *paths: str) -> None:
    """Delete folders that operators made."""
    conf = spark._jsparkSession.sessionState().newHadoopConf()
    for p in paths:
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(p)
        path.getFileSystem(conf).delete(path, True)


def written(df: DataFrame, label: str, path: str | None = None, partition_by: tuple = ()) -> DataFrame:
    """Write df to the shared folder as Parquet and read it back, which cuts its lineage."""
    spark, path = df.sparkSession, path or new_path(df.sparkSession, label)
    df.write.partitionBy(*partition_by).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def release(spark: SparkSession) -> None:
    """Let Spark remove the shuffle files behind what has been written.

    It does so once the driver has collected the objects that stand for them, which it may not
    do for half an hour of its own; operators with several large exchanges ask for it. Python's
    references are dropped on a thread of their own, so a second round finds what they held.
    """
    for _ in (1, 2):
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        time.sleep(0.5)


def input_bytes(df: DataFrame, column: str = "text") -> int:
    """Catalyst's estimate of df's size, from file sizes; where it has none or multiplies joined sizes, the measured bytes of `column`."""
    plan = df._jdf.queryExecution().optimizedPlan()
    estimate = int(str(plan.stats().sizeInBytes()))
    return estimate if estimate < 1 << 60 and "Join" not in plan.toString() else int(df.agg(F.sum(F.octet_length(column).cast("long"))).first()[0] or 0)


def partitions_for(df: DataFrame, bytes_each: int, least: int = 1) -> int:
    return max(least, -(-input_bytes(df) // bytes_each))


def free_name(df: DataFrame, name: str) -> str:
    """`name`, with as many underscores before it as make it no column of df."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name


def crc_bucket(doc_id: int | None, n: int) -> int:
    """crc32(doc_id as text) mod n; a null id counts as the empty text."""
    return zlib.crc32(b"" if doc_id is None else str(doc_id).encode()) % n


def texts(column: pa.Array) -> list[bytes]:
    """UTF-8 of every value, null as empty."""
    return [x or b"" for x in column.cast(pa.large_binary()).to_pylist()]


class HashCache(dict):
    """64-bit hashes of words, kept for as long as they fit in `limit` entries."""

    def __init__(self, limit: int = 200_000):
        super().__init__()
        self.limit = limit

    def __missing__(self, word: bytes) -> int:
        h = xxhash.xxh64_intdigest(word)
        if len(self) < self.limit:
            self[word] = h
        return h

    def of(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), dtype=np.uint64, count=len(words))


_WORD_HASHES = HashCache()


def word_hashes(words: list[bytes]) -> np.ndarray:
    """uint64 per word; the cache lives as long as the Python worker."""
    return _WORD_HASHES.of(words)


def mixed(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Ordered 64-bit combination of two arrays of hashes."""
    with np.errstate(over="ignore"):
        x = a * np.uint64(0x9E3779B97F4A7C15)
        x ^= x >> np.uint64(32)
        x += b
        x *= np.uint64(0xD6E8FEB86659FD93)
        x ^= x >> np.uint64(29)
    return x


def batches(rows: Iterator[pa.RecordBatch], most_bytes: int) -> Iterator[pa.RecordBatch]:
    """The same rows in batches that hold about most_bytes at most (one row at least)."""
    for batch in rows:
        parts = max(1, min(batch.num_rows, -(-batch.nbytes // most_bytes)))
        step = max(1, -(-batch.num_rows // parts))
        for at in range(0, batch.num_rows, step):
            yield batch.slice(at, step)
