"""Loaders: the same batches, asked for in different ways, before the same consumer.

Every loader yields regime, epoch, node_id, ready and turn of its batches; `consumed`
adds the consumer, and `epoch_times` sums up.
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Column, DataFrame, functions as F
from pyspark.sql.types import LongType, StructField, StructType

from ..config import FEED, Feed, Power
from ..functions.columns import div
from . import transport as T

NODE = ["regime", "epoch", "node_id"]


def _in_turn(df: DataFrame) -> DataFrame:
    from pyspark.sql import Window as W

    return df.withColumn("turn", F.row_number().over(W.partitionBy(*NODE).orderBy("batch_seq", "worker")).cast("long"))


def push_batch(batches: DataFrame, regimes: DataFrame, feed: Feed = FEED, delivery: str = "arrival", pipelined: bool = True, prebatched: bool = True) -> DataFrame:
    """Batches are pushed over one stream a worker. Not prebatched: a round trip and a send per record."""
    b = T.services(batches, feed).crossJoin(F.broadcast(regimes))
    if not prebatched:
        b = b.withColumn("send_us", F.col("send_us") + F.col("n") * (F.col("rtt_us") + feed.pack_us))
    d = T.pipeline_times(b) if pipelined else T.serial_times(b)
    return T.delivered(T.arrivals(d), delivery)


def push_bounded(batches: DataFrame, regimes: DataFrame, feed: Feed = FEED) -> DataFrame:
    """push_batch with the sender's high-water mark and the receiver's prefetch depth; adds done."""
    b = T.services(batches, feed).crossJoin(F.broadcast(regimes))
    return T.bounded_times(T.pipeline_times(b), feed.step_us, feed.hwm, feed.depth)


def pull_sample(batches: DataFrame, regimes: DataFrame, feed: Feed = FEED, local_only: bool = False, cached_epochs: bool = False) -> DataFrame:
    """Each record is asked for on demand. cached_epochs: no round trip from the second epoch on."""
    b = batches.crossJoin(F.broadcast(regimes))
    rtt = F.lit(0).cast("long") if local_only else F.when(F.col("epoch") > 1, F.lit(0).cast("long")).otherwise(F.col("rtt_us")) if cached_epochs else F.col("rtt_us")
    size = F.col("bytes") * feed.size_scale
    fetch = F.col("n") * (div(rtt * feed.sample_rtts_permille, 1000) + feed.decode_us) + div(size * 1_000_000, feed.net_bytes_s) + div(size * 1_000_000, feed.disk_bytes_s)
    b = _in_turn(b.withColumn("fetch_us", fetch))
    return T.queue_done(b, NODE, ["turn"], F.col("fetch_us"), "ready")


def pull_pipeline(batches: DataFrame, regimes: DataFrame, feed: Feed = FEED, rtt: Column | None = None) -> DataFrame:
    """Reads ahead through the mount: round trips overlap with the transfer, not with each other.

    rtt: the round trip of each batch, where it is not the regime's.
    """
    b = batches.crossJoin(F.broadcast(regimes))
    trip = F.col("rtt_us") if rtt is None else rtt
    size = F.col("bytes") * feed.size_scale
    reads = F.col("n") * F.greatest(F.lit(1).cast("long"), div(size + F.col("n") * feed.read_bytes - 1, F.col("n") * feed.read_bytes))
    fetch = F.greatest(div(reads * trip * feed.pipeline_rtts_permille, 1000), div(size * 1_000_000, feed.net_bytes_s) + div(size * 1_000_000, feed.disk_bytes_s))
    b = _in_turn(b.withColumn("fetch_us", fetch))
    return T.queue_done(b, NODE, ["turn"], F.col("fetch_us"), "ready")


def double_buffered(batches: DataFrame, regimes: DataFrame, feed: Feed = FEED) -> DataFrame:
    """Record-wise fetching with one batch of look-ahead: fetch i starts when batch i - 2 is consumed."""
    d = pull_sample(batches, regimes, feed)
    return lookahead(d, "fetch_us", feed.step_us, 2)


def lookahead(df: DataFrame, service: str, step_us: int, depth: int) -> DataFrame:
    """Serve batches with at most `depth` of them unconsumed; adds ready and done.

    The lag makes it a loop, run for one node's epoch at a time.
    """
    import pandas as pd

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("turn").reset_index(drop=True)
        s, n = pdf[service].tolist(), pdf.n.tolist()
        ready, done = [], []
        for i in range(len(pdf)):
            start = max(ready[-1] if ready else 0, done[i - depth] if i >= depth else 0)
            ready.append(start + s[i])
            done.append(max(done[-1] if done else 0, ready[i]) + n[i] * step_us)
        return pdf.assign(ready=ready, done=done)

    base = df.drop("ready", "done")
    schema = StructType([*base.schema.fields, StructField("ready", LongType()), StructField("done", LongType())])
    return base.groupBy(*NODE).applyInPandas(run, schema)


def consumed(df: DataFrame, feed: Feed = FEED) -> DataFrame:
    """Add done: batches are used in turn, step_us a record."""
    return df if "done" in df.columns else T.queue_done(df, NODE, ["turn"], F.col("n") * feed.step_us, "done", F.col("ready"))


def epoch_times(done: DataFrame) -> DataFrame:
    """regime, epoch, modelled_us (of the slowest node), busy_us, records, bytes, nodes."""
    by = done.groupBy("regime", "rtt_us", "epoch", "node_id").agg(F.max("done").alias("t"), F.sum("n").alias("n"), F.sum("bytes").alias("b"))
    return by.groupBy("regime", "rtt_us", "epoch").agg(F.max("t").alias("modelled_us"), F.sum("n").alias("records"), F.sum("b").alias("bytes"), F.count("*").alias("nodes"))


def cells(batches: DataFrame, regimes: DataFrame, feed: Feed, power: Power, loaders: tuple = ("push_batch", "pull_pipeline", "pull_sample")) -> DataFrame:
    """loader x regime: modelled time and component energies of all epochs."""
    make = {"push_batch": push_batch, "push_bounded": push_bounded, "pull_pipeline": pull_pipeline, "pull_sample": pull_sample}
    out = None
    for name in loaders:
        t = epoch_times(consumed(make[name](batches, regimes, feed), feed)).withColumn("loader", F.lit(name))
        out = t if out is None else out.unionByName(t)
    by = out.groupBy("loader", "regime", "rtt_us").agg(F.sum("modelled_us").alias("modelled_us"), F.sum("records").alias("records"), F.sum("bytes").alias("bytes"), F.max("nodes").alias("nodes"))
    idle, busy = dict(power.idle), dict(power.busy)
    energy = [(F.col("modelled_us") * F.col("nodes") * idle[c] + F.col("records") * feed.step_us * busy[c]).alias(f"{c}_uj") for c in ("cpu", "dram", "gpu")]
    return by.select("loader", "regime", "rtt_us", "records", (F.col("bytes") * feed.size_scale).alias("bytes"), "modelled_us", *energy)


def scaled(feed: Feed, **changes) -> Feed:
    return replace(feed, **changes)
