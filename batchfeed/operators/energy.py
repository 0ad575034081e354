"""Energy measurement: tick alignment, merge, interpolation and interval queries.

Slot k covers [k * delta, (k + 1) * delta) microseconds. A channel's slot energy is the
mean of its readings times delta; GPU energy adds its devices. All sums are integers,
so they do not depend on the order of rows.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame, Window as W, functions as F

from ..config import DAY_US, HOUR_US
from ..functions.cells import cell_of, known_neighbours, running_sums, spread
from ..functions.columns import div, micros

PARTS = ("cpu_uj", "dram_uj", "gpu_uj")
#: Slots that one task of a node takes at most.
CELL_SLOTS = 1 << 14


def align(samples: DataFrame, delta_us: int = HOUR_US, offsets: DataFrame | None = None) -> DataFrame:
    """Add `slot`; offsets(node_id, offset_us) corrects clocks and is one row a node."""
    t = micros(F.col("ts"))
    if offsets is not None:
        samples = samples.join(F.broadcast(offsets), "node_id", "left")
        t = t + F.coalesce("offset_us", F.lit(0))
    return samples.withColumn("slot", div(t, delta_us)).drop("offset_us")


def channel_energy(aligned: DataFrame, delta_us: int = HOUR_US) -> DataFrame:
    """node_id, slot, component, device, energy_uj: one row per channel with a reading."""
    by = aligned.groupBy("node_id", "slot", "component", "device").agg(F.sum("power_cw").alias("total"), F.count("*").alias("n"))
    return by.select("node_id", "slot", "component", "device", div(F.col("total") * F.lit(delta_us), F.col("n") * 100).alias("energy_uj"))


def counter_deltas(counters: DataFrame, modulus: int) -> DataFrame:
    """Add `delta`, what a cumulative counter(node_id, component, device, ts, counter) has grown by since its last reading.

    A counter that is below its last reading has wrapped at the modulus, once. First readings have none.
    """
    before = F.lag("counter").over(W.partitionBy("node_id", "component", "device").orderBy("ts"))
    return counters.withColumn("delta", F.pmod(F.col("counter") - before, F.lit(modulus)))


def counter_energy(aligned: DataFrame, delta_us: int = HOUR_US) -> DataFrame:
    """CPU and DRAM energy per slot."""
    c = channel_energy(aligned.where(F.col("component").isin("cpu", "dram")), delta_us)
    pick = lambda k: F.sum(F.when(F.col("component") == k, F.col("energy_uj")))
    return c.groupBy("node_id", "slot").agg(pick("cpu").alias("cpu_uj"), pick("dram").alias("dram_uj"))


def gpu_energy(aligned: DataFrame, delta_us: int = HOUR_US, devices: int = 2, require_all: bool = True) -> DataFrame:
    """GPU energy per slot; a slot without a reading of each device is a hole if require_all."""
    g = channel_energy(aligned.where(F.col("component") == "gpu"), delta_us).groupBy("node_id", "slot").agg(F.sum("energy_uj").alias("gpu_uj"), F.count("*").alias("n_devices"))
    return (g.where(F.col("n_devices") == devices) if require_all else g).drop("n_devices")


def merge_components(aligned: DataFrame, delta_us: int = HOUR_US, devices: int = 2) -> DataFrame:
    """One wide row per node and slot, by one conditional aggregation instead of outer joins."""
    c = channel_energy(aligned, delta_us)
    pick = lambda k: F.sum(F.when(F.col("component") == k, F.col("energy_uj")))
    g = F.when(F.count(F.when(F.col("component") == "gpu", 1)) == devices, pick("gpu"))
    return c.groupBy("node_id", "slot").agg(pick("cpu").alias("cpu_uj"), pick("dram").alias("dram_uj"), g.alias("gpu_uj")).where("cpu_uj IS NOT NULL OR dram_uj IS NOT NULL OR gpu_uj IS NOT NULL")


def merge_outer(aligned: DataFrame, delta_us: int = HOUR_US) -> DataFrame:
    """The same by full outer joins; kept to compare plans."""
    return counter_energy(aligned, delta_us).join(gpu_energy(aligned, delta_us), ["node_id", "slot"], "full")


def tick_grid(wide: DataFrame, cell_slots: int = CELL_SLOTS) -> DataFrame:
    """All expected (node, slot): each node has the slots from the first to the last of any node."""
    per = wide.groupBy("node_id").agg(F.min("slot").alias("a"), F.max("slot").alias("z"))
    every = W.partitionBy(F.lit(0))  # over one row a node
    nodes = per.select("node_id", F.min("a").over(every).alias("a"), F.max("z").over(every).alias("z"))
    return spread(nodes, "a", "z", "slot", cell_slots).select("node_id", "slot")


def on_grid(wide: DataFrame, cell_slots: int = CELL_SLOTS) -> DataFrame:
    return tick_grid(wide, cell_slots).join(wide, ["node_id", "slot"], "left")


def fill(full: DataFrame, method: str = "linear", edges: str = "hold", max_gap: int | None = None, cell_slots: int = CELL_SLOTS) -> DataFrame:
    """Fill the holes of gap-free rows; adds `<part>_filled`.

    method: linear, previous, nearest (ties: earlier), none. edges: hold or null, where one
    side has no reading. max_gap: longest run of holes to fill. A component that a node
    never has stays null. The nearest known slots are carried over cells of cell_slots.
    """
    if method == "none":
        return full.select("*", *(F.lit(False).alias(f"{p}_filled") for p in PARTS))
    near = known_neighbours(full, "node_id", "slot", PARTS, cell_slots)
    k, out = F.col("slot"), []
    for part in PARTS:
        p, q, own = F.col(f"{part}_p"), F.col(f"{part}_q"), F.col(part)
        inner = p.isNotNull() & q.isNotNull()
        if method == "linear":
            span = q["at"] - p["at"]
            value = F.when(span == 0, p["v"]).when(inner, div(p["v"] * span + (q["v"] - p["v"]) * (k - p["at"]), span))
        elif method == "previous":
            value = F.when(inner, p["v"])
        elif method == "nearest":
            value = F.when(inner, F.when(k - p["at"] <= q["at"] - k, p["v"]).otherwise(q["v"]))
        else:
            raise ValueError(method)
        if edges == "hold":
            value = F.when(inner, value).otherwise(F.coalesce(p["v"], q["v"]))
        if max_gap is not None:
            value = F.when(~inner | (q["at"] - p["at"] - 1 <= max_gap), value)
        value = F.coalesce(own, value)
        out += [value.alias(part), (own.isNull() & value.isNotNull()).alias(f"{part}_filled")]
    return near.select("node_id", "slot", *out)


def tuples(samples: DataFrame, delta_us: int = HOUR_US, **options) -> DataFrame:
    """Aligned, merged, gap-free and filled rows of samples."""
    return fill(on_grid(merge_components(align(samples, delta_us), delta_us)), **options)


def writer_batches(rows: DataFrame, size: int, cell_slots: int = CELL_SLOTS) -> DataFrame:
    """Number the batches of at most size rows a node in slot order."""
    return running_sums(rows, ["node_id"], ["slot"], cell_of("slot", cell_slots), {"_n": F.lit(1)}).withColumn("batch_no", div(F.col("_n"), size)).drop("_n")


def overlap_us(delta_us: int, start: Column, end: Column) -> Column:
    """Microseconds of slot inside [start, end)."""
    a = F.col("slot") * F.lit(delta_us)
    return F.greatest(F.lit(0).cast("long"), F.least(end, a + F.lit(delta_us)) - F.greatest(start, a))


def interval_energy(rows: DataFrame, intervals: DataFrame, delta_us: int = HOUR_US, edges: str = "whole", bucket_us: int = DAY_US) -> DataFrame:
    """Energy per interval(run_id, node_id, start_us, end_us) by a bucketed range join.

    Intervals are cut into the time buckets they touch, so the join is on (node, bucket).
    whole: slots that start inside; prorated: each by its overlap.
    """
    part = intervals.withColumn("bucket", F.explode(F.sequence(div(F.col("start_us") - delta_us, bucket_us), div(F.col("end_us"), bucket_us))))
    keyed = rows.withColumn("bucket", div(F.col("slot") * delta_us, bucket_us))
    j = keyed.join(part, ["node_id", "bucket"])
    at = F.col("slot") * F.lit(delta_us)
    if edges == "whole":
        hit, weight = (at >= F.col("start_us")) & (at < F.col("end_us")), None
    else:
        weight = overlap_us(delta_us, F.col("start_us"), F.col("end_us"))
        hit = weight > 0
    energy = lambda c: F.col(c) if weight is None else div(F.col(c) * div(weight, 1000), delta_us // 1000)
    sums = j.where(hit).groupBy("run_id", "node_id").agg(F.count("*").alias("n_slots"), *(F.sum(energy(c)).alias(c) for c in PARTS))
    return intervals.select("run_id", "node_id").join(sums, ["run_id", "node_id"], "left").withColumn("n_slots", F.coalesce("n_slots", F.lit(0).cast("long")))


def interval_energy_prefix(rows: DataFrame, intervals: DataFrame, delta_us: int = HOUR_US, cell_slots: int = CELL_SLOTS) -> DataFrame:
    """The whole-slot interval query as the difference of two running totals.

    A gap-free grid makes the as-of lookups equality joins on (node, slot); whatever the
    interval's length, it costs two rows.
    """
    run = running_sums(rows, ["node_id"], ["slot"], cell_of("slot", cell_slots), {f"{c}_run": F.col(c) for c in PARTS})
    run = run.select("node_id", "slot", *(F.col(f"{c}_run").alias(c) for c in PARTS))
    span = rows.groupBy("node_id").agg(F.min("slot").alias("lo"), F.max("slot").alias("hi"), *(F.coalesce(F.sum(c), F.lit(0)).alias(f"{c}_all") for c in PARTS))
    first = lambda t: F.call_function("ceil", F.col(t) / F.lit(delta_us)).cast("long")
    i = intervals.join(F.broadcast(span), "node_id").withColumn("a", F.greatest(first("start_us"), F.col("lo"))).withColumn("z", F.greatest(first("end_us"), F.col("lo")))
    at = lambda name: run.select("node_id", F.col("slot").alias(name), *(F.col(c).alias(f"{c}_{name}") for c in PARTS))
    j = i.join(at("a"), ["node_id", "a"], "left").join(at("z"), ["node_id", "z"], "left")
    total = lambda c, name: F.coalesce(f"{c}_{name}", f"{c}_all")
    return j.select("run_id", "node_id", *((total(c, "z") - total(c, "a")).alias(c) for c in PARTS))


def cluster_series(rows: DataFrame) -> DataFrame:
    return rows.groupBy("slot").agg(*(F.sum(c).alias(c) for c in PARTS))


def long_form(rows: DataFrame) -> DataFrame:
    """node_id, slot, component, energy_uj."""
    return rows.unpivot(["node_id", "slot"], list(PARTS), "component", "energy_uj").where("energy_uj IS NOT NULL")


def idle_baseline(rows: DataFrame, share: float = 0.05) -> DataFrame:
    """node_id, component, idle_uj: low quantile of the slot energies (lower value, exact)."""
    counts = long_form(rows).groupBy("node_id", "component", "energy_uj").agg(F.count("*").alias("c"))
    by = W.partitionBy("node_id", "component")  # over distinct values, counted before
    ranked = counts.withColumn("upto", F.sum("c").over(by.orderBy("energy_uj"))).withColumn("n", F.sum("c").over(by))
    at = F.floor((F.col("n") - 1) * F.lit(share)).cast("long") + 1
    return ranked.where((F.col("upto") >= at) & (F.col("upto") - F.col("c") < at)).select("node_id", "component", F.col("energy_uj").alias("idle_uj"))


def usage_energy(rows: DataFrame, idle: DataFrame) -> DataFrame:
    """Total, idle part and what is above it, per node and component."""
    total = long_form(rows).groupBy("node_id", "component").agg(F.sum("energy_uj").alias("total_uj"), F.count("*").alias("n_slots"))
    j = total.join(idle, ["node_id", "component"])
    above = F.col("total_uj") - F.col("idle_uj") * F.col("n_slots")
    return j.select("node_id", "component", "total_uj", (F.col("idle_uj") * F.col("n_slots")).alias("idle_total_uj"), above.alias("raw_usage_uj"), F.greatest(above, F.lit(0)).alias("usage_uj"))


def trace_quality(rows: DataFrame) -> DataFrame:
    """Coverage, filled slots, mean and peak energy of each node."""
    filled = lambda c: F.count(F.when(F.col(f"{c}_filled"), 1)).alias(f"{c}_filled")
    return rows.groupBy("node_id").agg(F.count("*").alias("n_slots"), *(filled(c) for c in PARTS), F.max("cpu_uj").alias("peak_cpu_uj"), F.max_by("slot", F.struct(F.col("cpu_uj"), -F.col("slot"))).alias("peak_slot"), div(F.sum("cpu_uj"), F.count("cpu_uj")).alias("mean_cpu_uj"))


def as_of(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """The last right value at or before each left row, by one union and one window."""
    a = left.withColumn("_side", F.lit(1)).withColumn(value, F.lit(None).cast(right.schema[value].dataType))
    b = right.select(key, at, value, F.lit(0).alias("_side"))
    both = a.unionByName(b, allowMissingColumns=True)
    w = W.partitionBy(key).orderBy(at, "_side").rowsBetween(W.unboundedPreceding, 0)
    return both.withColumn(value, F.last(value, ignorenulls=True).over(w)).where("_side = 1").drop("_side")


def trace_from_busy(busy: DataFrame, power, delta_us: int) -> DataFrame:
    """Slot energies of busy intervals(node_id, start_us, end_us): idle and busy watts."""
    s = busy.withColumn("slot", F.explode(F.sequence(div(F.col("start_us"), delta_us), div(F.col("end_us") - 1, delta_us))))
    used = s.groupBy("node_id", "slot").agg(F.sum(overlap_us(delta_us, F.col("start_us"), F.col("end_us"))).alias("busy_us"))
    idle, active = dict(power.idle), dict(power.busy)
    return used.select("node_id", "slot", *((F.lit(idle[c]) * F.lit(delta_us) + F.lit(active[c]) * F.col("busy_us")).cast("long").alias(f"{c}_uj") for c in ("cpu", "dram", "gpu")))


def trapezoid():
    """An aggregate over (t_us, power_cw) in any order: twice the integral of the power, by trapezoids between readings."""

    @F.pandas_udf("long")
    def twice(t: pd.Series, power: pd.Series) -> int:
        order = t.to_numpy().argsort(kind="stable")
        a, p = t.to_numpy()[order], power.to_numpy()[order]
        return int(((a[1:] - a[:-1]) * (p[1:] + p[:-1])).sum())

    return twice


def local_stores(rows: DataFrame, path: str) -> None:
    """Every node's rows in a store of its own."""
    rows.write.partitionBy("node_id").parquet(path)


def central_store(rows: DataFrame, path: str, delta_us: int = HOUR_US) -> None:
    """All rows in one table, by day."""
    rows.withColumn("day", div(F.col("slot") * delta_us, DAY_US)).write.partitionBy("day").parquet(path)
