"""Measures over cells (loader x regime): ratios, shares, fronts."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window as W, functions as F

from ..functions.columns import ratio


def speedup(cells: DataFrame, base: str = "push_batch") -> DataFrame:
    """Time of each loader over that of `base` at the same round trip."""
    b = cells.where(F.col("loader") == base).select("regime", F.col("modelled_us").alias("_b"))
    return cells.join(F.broadcast(b), "regime").select("loader", "regime", ratio(F.col("modelled_us"), F.col("_b")).alias("slower"))


def energy_ratio(cells: DataFrame, base: str = "push_batch") -> DataFrame:
    b = cells.where(F.col("loader") == base).select("regime", *(F.col(f"{c}_uj").alias(f"_{c}") for c in ("cpu", "dram", "gpu")))
    return cells.join(F.broadcast(b), "regime").select("loader", "regime", *(ratio(F.col(f"{c}_uj"), F.col(f"_{c}")).alias(f"{c}_ratio") for c in ("cpu", "dram", "gpu")))


def rtt_invariance(cells: DataFrame) -> DataFrame:
    """Spread of a loader's times over the regimes, relative to the least; flat: under 5 %."""
    off = F.max("modelled_us") - F.min("modelled_us")
    return cells.groupBy("loader").agg(ratio(off, F.min("modelled_us")).alias("spread"), (off * 20 < F.min("modelled_us")).alias("is_flat"))


def slowdown_own(cells: DataFrame) -> DataFrame:
    """Time of each loader over its own at the least round trip."""
    w = W.partitionBy("loader").orderBy("rtt_us")
    return cells.select("loader", "regime", ratio(F.col("modelled_us"), F.first("modelled_us").over(w)).alias("slower_than_nearest"))


def energy_cut(cells: DataFrame, base: str = "push_batch") -> DataFrame:
    """What `base` saves of each loader's component energies, in percent, and how much slower the loader is."""
    parts = ("cpu", "dram", "gpu")
    b = cells.where(F.col("loader") == base).select("regime", F.col("modelled_us").alias("_t"), *(F.col(f"{c}_uj").alias(f"_{c}") for c in parts))
    cuts = [ratio(100 * (F.col(f"{c}_uj") - F.col(f"_{c}")), F.col(f"{c}_uj")).alias(f"{c}_cut") for c in parts]
    return cells.join(F.broadcast(b), "regime").select("loader", "regime", ratio(F.col("modelled_us"), F.col("_t")).alias("slower"), *cuts)


def stage_shares(stages: DataFrame) -> DataFrame:
    """Cumulative stage times and energies (regime, stage_no, us, uj) with each stage's own and its share."""
    w, whole = W.partitionBy("regime").orderBy("stage_no"), W.partitionBy("regime")
    own = lambda c: F.col(c) - F.coalesce(F.lag(c).over(w), F.lit(0))
    d = stages.withColumn("own_us", own("us")).withColumn("own_uj", own("uj"))
    return d.withColumn("share", ratio(F.col("own_us"), F.max("us").over(whole))).withColumn("energy_share", ratio(F.col("own_uj"), F.max("uj").over(whole)))


def io_shares(stages: DataFrame) -> DataFrame:
    """Shares of reading, and of reading with preprocessing, of the time and energy of an epoch."""
    at = lambda c, k: F.max(F.when(F.col("stage_no") == k, F.col(c)))
    return stages.groupBy("regime").agg(ratio(at("us", 1), F.max("us")).alias("share"), ratio(at("uj", 1), F.max("uj")).alias("energy_share"), ratio(at("us", 2), F.max("us")).alias("fetch_share"), ratio(at("uj", 2), F.max("uj")).alias("fetch_energy_share"))


def edp(cells: DataFrame) -> DataFrame:
    """Energy-delay product in J s."""
    e = (F.col("cpu_uj") + F.col("dram_uj") + F.col("gpu_uj")) / F.lit(1e6)
    return cells.select("loader", "regime", (F.floor(e * (F.col("modelled_us") / F.lit(1e6)) * 1e3 + 0.5) / F.lit(1e3)).alias("edp"))


def pareto_front(cells: DataFrame) -> DataFrame:
    """Cells that no cell of the same regime beats in time and energy."""
    t = cells.select("loader", "regime", F.col("modelled_us").alias("t"), (F.col("cpu_uj") + F.col("dram_uj") + F.col("gpu_uj")).alias("e"))
    o = t.select("regime", F.col("t").alias("t2"), F.col("e").alias("e2"))
    beaten = (t.regime == o.regime) & (o.t2 <= t.t) & (o.e2 <= t.e) & ((o.t2 < t.t) | (o.e2 < t.e))
    return t.join(F.broadcast(o), beaten, "left_anti").select("loader", "regime", F.col("t").alias("modelled_us"), F.col("e").alias("energy_uj"))


def carbon(cells: DataFrame, g_per_kwh: int = 458) -> DataFrame:
    """kWh and grams of CO2 of each cell."""
    e = (F.col("cpu_uj") + F.col("dram_uj") + F.col("gpu_uj")).cast("double")
    return cells.select("loader", "regime", (F.floor(e / 3.6e12 * 1e9 + 0.5) / F.lit(1e9)).alias("kwh"), (F.floor(e / 3.6e12 * g_per_kwh * 1e6 + 0.5) / F.lit(1e6)).alias("co2_g"))
