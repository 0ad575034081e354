"""The live monitor: aligned energy, smoothing, sessions, run-log joins and hole filling.

Streams carry TIMESTAMP (UTC), as watermarks ask for. `run_once` reads what is there
(AvailableNow) into Parquet; in append mode windows still open at the end stay out.
"""

from __future__ import annotations

import contextlib

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.streaming import StatefulProcessor

from ..sources.tables import samples_of
from .sinks import run_once

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str, files_each: int | None = None) -> DataFrame:
    """Events as a stream, from events.parquet as a file or a folder of part files.

    files_each bounds what one trigger admits; without it a bounded run takes all files
    in one, so that no row of a later file is late.
    """
    jvm = spark.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(f"{sf_dir}/events.parquet")
    fs = path.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf())
    folder = fs.exists(path) and fs.getFileStatus(path).isDirectory()
    reader = spark.readStream.schema(EVENTS)
    if files_each is not None:
        reader = reader.option("maxFilesPerTrigger", files_each)
    raw = reader.parquet(f"{sf_dir}/events.parquet") if folder else reader.option("pathGlobFilter", "events.parquet*").parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def sample_stream(spark: SparkSession, sf_dir: str, delay: str = "1 hour") -> DataFrame:
    return samples_of(event_stream(spark, sf_dir)).withWatermark("ts", delay)


def _ends(df: DataFrame) -> DataFrame:
    return df.withColumns({"start_ts": F.col("window.start").cast("timestamp_ntz"), "end_ts": F.col("window.end").cast("timestamp_ntz")}).drop("window")


def tick_energy(samples: DataFrame, every: str = "1 hour") -> DataFrame:
    """Sum and count of readings per node, component, device and tick."""
    return _ends(samples.groupBy("node_id", "component", "device", F.window("ts", every)).agg(F.sum("power_cw").alias("total_cw"), F.count("*").alias("n")))


def sliding_power(samples: DataFrame, width: str = "6 hours", every: str = "1 hour") -> DataFrame:
    return _ends(samples.groupBy("node_id", F.window("ts", width, every)).agg(F.sum("power_cw").alias("total_cw"), F.count("*").alias("n")))


def sessions(samples: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """Bursts of readings of a node with no pause of `gap`."""
    s = samples.groupBy("node_id", F.session_window("ts", gap).alias("window")).agg(F.count("*").alias("n"))
    return _ends(s)


def send_receipt(events: DataFrame, within: str = "1 hour", delay: str = "1 hour") -> DataFrame:
    """Views (sends) joined with clicks (receipts) of the same node within an hour.

    A stream join compares all rows of a key, so time is part of the key: a receipt has the
    quarter of `within` it falls in, a send has all that its receipts can fall in. A pair meets
    in the receipt's quarter alone, and a key holds the rows of a stretch of time.
    """
    node = (F.col("user_id") % 4).cast("int")
    width = f"greatest(1, unix_micros(timestamp_micros(0) + INTERVAL {within}) div 4)"
    quarter = lambda t: F.expr(f"unix_micros({t}) div {width}")
    s = events.where("event_type = 'view'").select(node.alias("node_id"), F.col("event_id").alias("send_id"), F.col("ts").alias("sent")).withWatermark("sent", delay)
    s = s.withColumn("quarter", F.explode(F.sequence(quarter("sent"), quarter(f"(sent + INTERVAL {within})"))))
    r = events.where("event_type = 'click'").select(node.alias("r_node"), F.col("event_id").alias("receipt_id"), F.col("ts").alias("received")).withWatermark("received", delay)
    r = r.withColumn("r_quarter", quarter("received"))
    on = (F.col("node_id") == F.col("r_node")) & (F.col("quarter") == F.col("r_quarter")) & (F.col("received") >= F.col("sent")) & (F.col("received") < F.col("sent") + F.expr(f"INTERVAL {within}"))
    return s.join(r, on).select("node_id", "send_id", "receipt_id")


def deduplicated(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Each event once, though delivered twice."""
    return events.unionByName(events).withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "event_type")


class FillHoles(StatefulProcessor):
    """Keeps a node's last known slot; a later slot closes the holes between."""

    def init(self, handle) -> None:
        self.last = handle.getValueState("last", "slot long, cpu_uj long")

    def handleInputRows(self, key, rows, timerValues):
        known = sorted(x for f in rows for x in zip(f.slot.tolist(), f.cpu_uj.tolist(), strict=True))
        last = self.last.get() if self.last.exists() else None
        out = []
        for slot, value in known:
            if last is not None:
                p, v = last
                out.extend((key[0], k, (v * (slot - p) + (value - v) * (k - p)) // (slot - p), True) for k in range(p + 1, slot))
            out.append((key[0], slot, value, False))
            last = (slot, value)
        if last is not None:
            self.last.update(tuple(last))
        yield pd.DataFrame(out, columns=["node_id", "slot", "cpu_uj", "filled"])

    def close(self) -> None:
        pass


def interpolated(ticks: DataFrame) -> DataFrame:
    """Hole filling with state: closed CPU ticks of each node, linear between known slots.

    Needs the RocksDB state store (`rocksdb_state`).
    """
    return ticks.groupBy("node_id").transformWithStateInPandas(FillHoles(), "node_id int, slot long, cpu_uj long, filled boolean", "Append", "None")


@contextlib.contextmanager
def rocksdb_state(spark: SparkSession):
    """Streams started inside keep their state in RocksDB; a setting of running sessions."""
    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key, None)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        yield
    finally:
        spark.conf.set(key, before) if before else spark.conf.unset(key)


def cpu_ticks(samples: DataFrame, delta_us: int = 3_600_000_000) -> DataFrame:
    """node_id, slot, cpu_uj of each closed tick."""
    t = samples.where("component = 'cpu'").groupBy("node_id", F.window("ts", f"{delta_us} microseconds")).agg(F.sum("power_cw").alias("s"), F.count("*").alias("n"))
    return t.select("node_id", F.call_function("div", F.unix_micros(F.col("window.start")), F.lit(delta_us)).alias("slot"), F.call_function("div", F.col("s") * delta_us, F.col("n") * 100).alias("cpu_uj"))
