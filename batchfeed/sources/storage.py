"""The shared folder: paths that the driver and all executors see, and files in it."""

from __future__ import annotations

import contextlib
import uuid

import pyarrow.fs as pafs
from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """`spark.checkpoint.dir` where it is set, else the context's checkpoint folder, else one in the warehouse."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        base = found.get() if found.isDefined() else spark.conf.get("spark.sql.warehouse.dir") + "/_shared"
    return base.rstrip("/")


def new_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/batchfeed-{label}-{uuid.uuid4().hex}"


def written(df: DataFrame, label: str, *partition_by: str) -> DataFrame:
    """df as Parquet in the shared folder, read back: computed once, and its lineage cut."""
    spark, path = df.sparkSession, new_path(df.sparkSession, label)
    df.write.partitionBy(*partition_by).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def file_system(uri: str) -> tuple[pafs.FileSystem, str]:
    """pyarrow's file system and path of a folder; s3a and s3n are s3 to it."""
    scheme, sep, rest = uri.partition("://")
    return pafs.FileSystem.from_uri(f"s3://{rest}" if scheme in ("s3a", "s3n") else uri)


def make_folder(uri: str) -> tuple[pafs.FileSystem, str]:
    fs, root = file_system(uri)
    with contextlib.suppress(FileExistsError):
        fs.create_dir(root, recursive=True)
    return fs, root
