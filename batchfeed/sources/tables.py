"""Typed adapters from the given tables to power samples and training records."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from ..config import NODES, REGIMES


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Event types that stand for the readings of a component.
EVENT_TYPES = {"cpu": ("view",), "dram": ("click",), "gpu": ("signup", "purchase")}


def samples_of(events: DataFrame, components: tuple[str, ...] = tuple(EVENT_TYPES)) -> DataFrame:
    """Power samples of the components: node_id, ts, component, device, power_cw (hundredths of a watt).

    Four nodes; node 3 has no GPU, error events are missed samples. The choice of components
    is one of event types, which the scan can apply.
    """
    kind = F.col("event_type")
    component = F.when(kind == "view", "cpu").when(kind == "click", "dram").when(kind.isin("signup", "purchase"), "gpu")
    rows = events.where(kind.isin(*(t for c in components for t in EVENT_TYPES[c])))
    rows = rows.select((F.col("user_id") % 4).cast("int").alias("node_id"), "ts", component.alias("component"), F.when(kind == "purchase", 1).otherwise(0).alias("device"), F.floor(F.col("value") * 100 + 0.5).cast("long").alias("power_cw"))
    return rows.where("NOT (node_id = 3 AND component = 'gpu')")


def samples(spark: SparkSession, sf_dir: str, *components: str) -> DataFrame:
    return samples_of(read(spark, sf_dir, "events"), components or tuple(EVENT_TYPES))


def nodes(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(NODES), "node_id int, role string, site string, has_gpu boolean, n_gpus int")


def regimes(spark: SparkSession, *names: str) -> DataFrame:
    return spark.createDataFrame([r for r in REGIMES if not names or r[0] in names], "regime string, rtt_us long")


def _records(df: DataFrame, shard: Column, record: Column, size: Column, label: Column) -> DataFrame:
    return df.select(shard.cast("string").alias("shard_id"), record.cast("long").alias("record_id"), size.cast("long").alias("size"), label.cast("int").alias("label"))


def records(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """shard_id, record_id, size, label of a sample set; payload columns are not read where sizes do."""
    if name == "documents":
        docs, labels = read(spark, sf_dir, "documents").select("doc_id", "source", F.octet_length("text").alias("n")), read(spark, sf_dir, "labels").select("doc_id", "quality")
        return _records(docs.join(labels, "doc_id", "left"), F.col("source"), F.col("doc_id"), F.col("n"), F.coalesce("quality", F.lit(-1)))
    if name == "pages":
        return _records(read(spark, sf_dir, "pages"), F.col("page_id") % 8, F.col("page_id"), F.octet_length("html"), F.lit(-1))
    if name == "embeddings":
        return _records(read(spark, sf_dir, "embeddings"), F.col("vec_id") % 8, F.col("vec_id"), F.lit(256), F.col("label"))
    if name == "conversations":
        talks = read(spark, sf_dir, "conversations").groupBy("conv_id").agg(F.sum(F.octet_length("text").cast("long")).alias("n"))
        return _records(talks, F.col("conv_id") % 4, F.col("conv_id"), F.col("n"), F.lit(-1))
    if name == "lineitem":
        rows = read(spark, sf_dir, "lineitem").groupBy("l_suppkey", "l_orderkey", "l_linenumber", "l_partkey", "l_shipdate").agg(F.max("l_quantity").alias("q"))
        return _records(rows, F.col("l_suppkey"), F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_shipdate"), F.lit(64) + F.col("q").cast("long"), F.lit(-1))
    raise ValueError(f"no sample set {name}")
