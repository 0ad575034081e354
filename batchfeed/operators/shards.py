"""Shard store: index of records in contiguous shards, and what it costs to build."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from ..config import FEED
from ..functions.cells import by_quantiles, running_sums
from ..functions.columns import div, ratio


def shard_index(records: DataFrame, header: int = FEED.header, cells: int = 64) -> DataFrame:
    """shard_id, ordinal, offset, size, label: each record behind a header, in record order.

    A shard's records are cut at quantiles of their ids into at most `cells` tasks, whose
    counts and bytes are carried from one to the next.
    """
    own = records.select("shard_id", "record_id", "size", "label")
    sums = {"ordinal": F.lit(1), "offset": F.col("size") + header}
    placed = running_sums(by_quantiles(own, "shard_id", "record_id", cells), ["shard_id"], ["record_id"], F.col("_q"), sums)
    return placed.select("shard_id", "record_id", "ordinal", "offset", "size", "label")


def shard_stats(records: DataFrame, header: int = FEED.header) -> DataFrame:
    """Counts and bytes per shard: all that the planner needs."""
    return records.groupBy("shard_id").agg(F.count("*").alias("n"), F.sum(F.col("size") + header).alias("bytes"), F.max("size").alias("largest"), ratio(F.sum("size"), F.count("*")).alias("mean_size"))


def label_histogram(records: DataFrame) -> DataFrame:
    return records.groupBy("shard_id", "label").agg(F.count("*").alias("n"))


def write_index_json(index: DataFrame, path: str, line_records: int = 10_000) -> None:
    """JSON lines of at most line_records successive records of a shard each."""
    cols = [c for c in index.columns if c not in ("shard_id", "ordinal")]
    rows = F.array_sort(F.collect_list(F.struct("ordinal", *cols)))
    index.groupBy("shard_id", div(F.col("ordinal"), line_records).alias("line")).agg(rows.alias("records")).write.json(path)


def read_index_json(spark, path: str, columns: str = "offset:long,size:long,label:int") -> DataFrame:
    schema = f"shard_id string, line long, records array<struct<ordinal:long,{columns}>>"
    return spark.read.schema(schema).json(path).selectExpr("shard_id", "inline(records)")


def amortized_cost(stats: DataFrame, jobs: int, us_per_byte: int = 1) -> DataFrame:
    """Conversion time shared by 1..jobs later jobs."""
    total = stats.agg((F.sum("bytes") * us_per_byte).alias("convert_us"))
    return total.select(F.explode(F.sequence(F.lit(1), F.lit(jobs))).alias("jobs"), "convert_us").select("jobs", "convert_us", F.call_function("div", "convert_us", F.col("jobs").cast("long")).alias("us_per_job"))
