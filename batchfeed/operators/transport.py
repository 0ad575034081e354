"""Transport model: stage times of batches in closed form, in integer microseconds.

A stage serves the batches of a stream one by one. With S the running sum of its
service times, batch i is done at S(i) + max over j <= i of (ready(j) - S(j - 1)): a
running sum and a running maximum over one sort, instead of an event loop.
"""

from __future__ import annotations

import heapq

from pyspark.sql import Column, DataFrame, Window as W, functions as F
from pyspark.sql.types import LongType, StructField, StructType

from ..config import FEED, Feed
from ..functions.columns import div

STREAM = ["regime", "epoch", "node_id", "worker"]


def queue_done(df: DataFrame, keys: list[str], order: list, service: Column, out: str, ready: Column | None = None) -> DataFrame:
    """Add `out`, when each row leaves a single server fed at `ready` (0 if absent)."""
    w = W.partitionBy(*keys).orderBy(*order).rowsBetween(W.unboundedPreceding, 0)
    s = F.sum(service).over(w)
    if ready is None:
        return df.withColumn(out, s)
    d = df.withColumn("_s", s).withColumn("_slack", ready - (F.col("_s") - service))
    return d.withColumn(out, F.col("_s") + F.max("_slack").over(w)).drop("_s", "_slack")


def services(batches: DataFrame, feed: Feed = FEED) -> DataFrame:
    """Add read_us, pack_us and send_us of each batch; the streams of a node share its links."""
    b = F.col("bytes") * feed.size_scale
    return batches.select(
        "*",
        (F.col("n_ranges") * feed.seek_us + div(b * feed.workers * 1_000_000, feed.disk_bytes_s)).alias("read_us"),
        (F.lit(feed.pack_us) + div(b * feed.pack_ns_byte, 1000)).alias("pack_us"),
        div(b * feed.workers * 1_000_000, feed.net_bytes_s).alias("send_us"),
    )


def pipeline_times(batches: DataFrame, keys: list[str] = STREAM) -> DataFrame:
    """Read, pack and send in parallel stages: read_done, pack_done, send_done."""
    d = queue_done(batches, keys, ["batch_seq"], F.col("read_us"), "read_done")
    d = queue_done(d, keys, ["batch_seq"], F.col("pack_us"), "pack_done", F.col("read_done"))
    return queue_done(d, keys, ["batch_seq"], F.col("send_us"), "send_done", F.col("pack_done"))


def serial_times(batches: DataFrame, keys: list[str] = STREAM) -> DataFrame:
    """The same stages one after the other, with a round trip for each batch."""
    return queue_done(batches, keys, ["batch_seq"], F.col("read_us") + F.col("pack_us") + F.col("send_us") + F.col("rtt_us"), "send_done")


def arrivals(done: DataFrame) -> DataFrame:
    """Arrival at the receiver: one connection set-up, then half a round trip."""
    return done.withColumn("arrival", F.col("send_done") + F.col("rtt_us") + div(F.col("rtt_us"), 2))


def delivered(df: DataFrame, how: str = "arrival", keys: tuple = ("regime", "epoch", "node_id")) -> DataFrame:
    """Add ready and turn: order of delivery at a node.

    arrival: as batches come; in_order: by (batch_seq, worker), so each waits for all before it.
    """
    if how == "arrival":
        w = W.partitionBy(*keys).orderBy("arrival", "worker", "batch_seq")
        return df.withColumn("turn", F.row_number().over(w).cast("long")).withColumn("ready", F.col("arrival"))
    w = W.partitionBy(*keys).orderBy("batch_seq", "worker")
    return df.withColumn("turn", F.row_number().over(w).cast("long")).withColumn("ready", F.max("arrival").over(w.rowsBetween(W.unboundedPreceding, 0)))


def rate_bound(batches: DataFrame, hwm: int = FEED.hwm, feed: Feed = FEED) -> DataFrame:
    """Bytes a second that hwm payloads in flight allow at each round-trip time, against the link."""
    by = batches.groupBy("regime", "rtt_us").agg(div(F.sum("bytes") * feed.size_scale, F.count("*")).alias("mean_bytes"))
    cap = F.when(F.col("rtt_us") > 0, div(F.col("mean_bytes") * hwm * 1_000_000, F.greatest("rtt_us", F.lit(1))))
    return by.select("regime", "rtt_us", "mean_bytes", cap.alias("window_bytes_s"), F.least(F.coalesce(cap, F.lit(feed.net_bytes_s)), F.lit(feed.net_bytes_s)).alias("bound_bytes_s"))


def bounded_times(done: DataFrame, step_us: int, hwm: int = FEED.hwm, depth: int = 1) -> DataFrame:
    """Sends under a high-water mark, before a consumer that prefetches.

    A stream starts a send only when it knows of all but at most hwm - 1 of its payloads that
    the node has taken them, half a round trip later. The node takes payloads as they come
    while fewer than `depth` of them are not used up; depth 1: each as the one before ends.
    Times of a sender count from its connection, one round trip after the receiver's clock starts.

    A lagged recurrence over merged streams, so one Arrow function per (regime, epoch, node)
    walks the batches of that node; its group is a node's plan, bounded by the epoch.
    """
    import pandas as pd

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["worker", "batch_seq"], kind="stable").reset_index(drop=True)
        rtt = int(pdf.rtt_us.iloc[0]) if len(pdf) else 0
        streams = {w: list(g.index) for w, g in pdf.groupby("worker")}
        place = dict.fromkeys(streams, 0)
        free = dict.fromkeys(streams, 0)
        taken: dict = {w: [] for w in streams}
        packed, send, n = pdf.pack_done.tolist(), pdf.send_us.tolist(), pdf.n.tolist()
        arrival, done = [0] * len(pdf), [0] * len(pdf)
        waiting: list = []
        ends: list[int] = []
        last = 0
        while any(place[w] < len(rows) for w, rows in streams.items()) or waiting:
            for w, rows in streams.items():
                while place[w] < len(rows) and place[w] - len(taken[w]) < hwm:
                    i = rows[place[w]]
                    gate = taken[w][place[w] - hwm] + rtt // 2 - rtt if place[w] >= hwm else 0
                    free[w] = max(free[w], packed[i], gate) + send[i]
                    arrival[i] = free[w] + rtt + rtt // 2
                    heapq.heappush(waiting, (arrival[i], w, place[w], i))
                    place[w] += 1
            at, w, _, i = heapq.heappop(waiting)
            last = max(last, at, ends[-depth] if len(ends) >= depth else 0)
            taken[w].append(last)
            done[i] = max(last, ends[-1] if ends else 0) + n[i] * step_us
            ends.append(done[i])
        return pdf.assign(arrival=arrival, done=done)

    schema = StructType([*done.schema.fields, StructField("arrival", LongType()), StructField("done", LongType())])
    return done.groupBy("regime", "epoch", "node_id").applyInPandas(run, schema)


def latency_profile(df: DataFrame, keys: list[str]) -> DataFrame:
    """Quantiles of the time from the start of reading to delivery of a batch."""
    wait = (F.col("ready") - (F.col("read_done") - F.col("read_us"))).cast("double")
    q = lambda p: (F.floor(F.percentile(wait, p) * 1e6 + 0.5) / F.lit(1e6)).alias(f"p{int(p * 100)}")
    return df.groupBy(*keys).agg(F.count("*").alias("n"), q(0.5), q(0.95), q(0.99), F.max(wait).alias("worst"))


def scale_out(stats: DataFrame, feed: Feed = FEED, servers: tuple = (1, 2, 4, 8)) -> DataFrame:
    """Makespan when shards are spread over 1, 2, 4, ... servers by rank."""
    k = (F.row_number().over(W.orderBy("shard_id")) - 1).cast("long")
    t = stats.withColumn("k", k).withColumn("servers", F.explode(F.array(*(F.lit(s).cast("long") for s in servers))))
    busy = t.groupBy("servers", (F.col("k") % F.col("servers")).alias("server")).agg(F.sum(F.lit(feed.seek_us) + div(F.col("bytes") * feed.size_scale * 1_000_000, feed.disk_bytes_s)).alias("us"), F.sum("bytes").alias("bytes"))
    return busy.groupBy("servers").agg(F.max("us").alias("makespan_us"), F.sum("us").alias("total_us"), div(F.sum("bytes") * feed.size_scale * 1_000_000, F.max("us")).alias("bytes_s"))
