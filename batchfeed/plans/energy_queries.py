"""Queries of the energy measurement."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window as W, functions as F

from ..config import DAY_US, HOUR_US
from ..functions.columns import div, micros, ratio, rounded
from ..operators import energy as E
from ..sources.tables import nodes, read, samples
from .registry import query

S = """samples as (select (user_id % 4)::int node_id, ts, case event_type when 'view' then 'cpu' when 'click' then 'dram' else 'gpu' end component,
 case event_type when 'purchase' then 1 else 0 end device, floor(value * 100 + 0.5)::bigint power_cw from events where event_type <> 'error' and not (user_id % 4 = 3 and event_type in ('signup', 'purchase'))),
a as (select *, epoch_us(ts) // 3600000000 slot from samples)"""
C = S + """, c as (select node_id, slot, component, device, ((sum(power_cw)::bigint * 3600000000) // (count(*) * 100))::bigint e from a group by all)"""
GPU = """select node_id, slot, sum(e)::bigint gpu_uj from c where component = 'gpu' group by all having count(*) = 2"""
WIDE = C + f""", w as (select node_id, slot, cpu_uj, dram_uj, gpu_uj from (select node_id, slot, e cpu_uj from c where component = 'cpu')
 full join (select node_id, slot, e dram_uj from c where component = 'dram') using (node_id, slot) full join ({GPU}) using (node_id, slot))"""
GRID = WIDE + """, g as (select node_id, slot from (select distinct node_id from w), (select unnest(range(min(slot), max(slot) + 1)) slot from w)), f as (select g.node_id, g.slot, cpu_uj, dram_uj, gpu_uj from g left join w using (node_id, slot))"""


def _filled(method: str, edges: str = "hold", gap: int | None = None) -> str:
    """Self-join form: the nearest known slots on both sides of each slot."""
    ctes, parts = [], []
    for c in ("cpu", "dram", "gpu"):
        ctes.append(f"""k{c} as (select f.node_id, f.slot, f.{c}_uj v, p.slot ps, p.{c}_uj pv, q.slot qs, q.{c}_uj qv
 from f asof left join (select * from f where {c}_uj is not null) p on f.node_id = p.node_id and f.slot >= p.slot
 asof left join (select * from f where {c}_uj is not null) q on f.node_id = q.node_id and f.slot <= q.slot)""")
        inner = {"linear": "coalesce((pv * (qs - ps) + (qv - pv) * (slot - ps)) // nullif(qs - ps, 0), pv)", "previous": "pv", "nearest": "case when slot - ps <= qs - slot then pv else qv end"}[method]
        edge = "coalesce(pv, qv)" if edges == "hold" else "null"
        near = f"case when pv is not null and qv is not null then {'case when qs - ps - 1 <= ' + str(gap) + ' then ' + inner + ' end' if gap is not None else inner} else {edge} end"
        ctes.append(f"x{c} as (select node_id, slot, coalesce(v, {near})::bigint {c}_uj, v is null and ({near}) is not null {c}_uj_filled from k{c})")
    return GRID + ", " + ", ".join(ctes) + """, t as (select node_id, slot, cpu_uj, cpu_uj_filled, dram_uj, dram_uj_filled, gpu_uj, gpu_uj_filled
 from xcpu join xdram using (node_id, slot) join xgpu using (node_id, slot))"""


T = _filled("linear")
LONG = T + """, l as (select node_id, slot, 'cpu_uj' component, cpu_uj e from t where cpu_uj is not null
 union all select node_id, slot, 'dram_uj', dram_uj from t where dram_uj is not null union all
 select node_id, slot, 'gpu_uj', gpu_uj from t where gpu_uj is not null)"""
RUNS = """, r as (select (node_id + 4 * (epoch_us(ts) // 86400000000 - 19723))::bigint run_id, node_id, epoch_us(min(ts)) start_us, epoch_us(max(ts)) end_us
 from samples group by node_id, epoch_us(ts) // 86400000000)"""


def tuples(spark: SparkSession, d: str, **options) -> DataFrame:
    return E.tuples(samples(spark, d), **options)


def runs(spark: SparkSession, d: str) -> DataFrame:
    """One interval a node and day, from its first to its last sample."""
    t = micros(F.col("ts"))
    by = samples(spark, d).groupBy("node_id", div(t, DAY_US).alias("day")).agg(F.min(t).alias("start_us"), F.max(t).alias("end_us"))
    return by.select((F.col("node_id") + 4 * (F.col("day") - 19723)).alias("run_id"), "node_id", "start_us", "end_us")


@query("tick_align", f"with {S} select node_id, component, device, slot, count(*) n, sum(power_cw)::bigint total_cw from a group by all")
def tick_align(spark, d):
    return E.align(samples(spark, d)).groupBy("node_id", "component", "device", "slot").agg(F.count("*").alias("n"), F.sum("power_cw").alias("total_cw"))


@query("counter_energy_slots", f"""with {C} select node_id, slot, sum(e) filter (component = 'cpu')::bigint cpu_uj, sum(e) filter (component = 'dram')::bigint dram_uj
 from c where component <> 'gpu' group by all""")
def counter_energy_slots(spark, d):
    return E.counter_energy(E.align(samples(spark, d)))


@query("gpu_energy_slots", f"with {C} {GPU}")
def gpu_energy_slots(spark, d):
    return E.gpu_energy(E.align(samples(spark, d)))


@query("gpu_energy_any_device", f"with {C} select node_id, slot, sum(e)::bigint gpu_uj from c where component = 'gpu' group by all")
def gpu_energy_any_device(spark, d):
    return E.gpu_energy(E.align(samples(spark, d)), require_all=False)


@query("merge_components", f"with {WIDE} select * from w")
def merge_components(spark, d):
    return E.merge_components(E.align(samples(spark, d)))


@query("merge_full_outer", f"with {WIDE} select * from w")
def merge_full_outer(spark, d):
    return E.merge_outer(E.align(samples(spark, d)))


@query("optional_gpu", f"""with {WIDE} select n.node_id, n.has_gpu, count(slot) n_slots, count(gpu_uj) n_gpu_slots from (values (0, true), (1, true), (2, true), (3, false)) n(node_id, has_gpu)
 left join w using (node_id) group by all""")
def optional_gpu(spark, d):
    wide = E.merge_components(E.align(samples(spark, d)))
    return F.broadcast(nodes(spark)).join(wide, "node_id", "left").groupBy("node_id", "has_gpu").agg(F.count("slot").alias("n_slots"), F.count("gpu_uj").alias("n_gpu_slots"))


@query("tick_grid_holes", f"""with {GRID} select node_id, count(*) n_slots, count(*) - count(cpu_uj) cpu_holes, count(*) - count(dram_uj) dram_holes, count(*) - count(gpu_uj) gpu_holes
 from f group by all""")
def tick_grid_holes(spark, d):
    full = E.on_grid(E.merge_components(E.align(samples(spark, d))))
    return full.groupBy("node_id").agg(F.count("*").alias("n_slots"), *((F.count("*") - F.count(f"{c}_uj")).alias(f"{c}_holes") for c in ("cpu", "dram", "gpu")))


for _name, _options in {
    "interpolate_linear": {"method": "linear"}, "interpolate_previous": {"method": "previous"}, "interpolate_nearest": {"method": "nearest"},
    "interpolate_max_gap": {"method": "linear", "max_gap": 2}, "interpolate_null_edges": {"method": "linear", "edges": "null"},
}.items():
    query(_name, f"with {_filled(_options['method'], _options.get('edges', 'hold'), _options.get('max_gap'))} select * from t")(lambda spark, d, o=_options: tuples(spark, d, **o))

query("interpolate_none", f"with {GRID} select *, false cpu_uj_filled, false dram_uj_filled, false gpu_uj_filled from f")(lambda spark, d: tuples(spark, d, method="none"))


@query("writer_batches", f"""with {T} select node_id, batch_no, count(*) n, min(slot) first_slot, max(slot) last_slot from (select *, (row_number() over (partition by node_id
 order by slot) - 1) // 100 batch_no from t) group by all""")
def writer_batches(spark, d):
    return E.writer_batches(tuples(spark, d), 100).groupBy("node_id", "batch_no").agg(F.count("*").alias("n"), F.min("slot").alias("first_slot"), F.max("slot").alias("last_slot"))


_WHOLE = f"""with {T} {RUNS} select run_id, r.node_id, count(slot) n_slots, sum(cpu_uj)::bigint cpu_uj, sum(dram_uj)::bigint dram_uj, sum(gpu_uj)::bigint gpu_uj
 from r left join t on r.node_id = t.node_id and slot * 3600000000 >= start_us and slot * 3600000000 < end_us
 group by all"""


@query("interval_energy_whole", _WHOLE)
def interval_energy_whole(spark, d):
    return E.interval_energy(tuples(spark, d), runs(spark, d))


@query("interval_energy_bucketed", _WHOLE)
def interval_energy_bucketed(spark, d):
    return E.interval_energy(tuples(spark, d), runs(spark, d), bucket_us=6 * HOUR_US)


_PRO = "".join(f", sum({c}_uj * (o // 1000) // 3600000)::bigint {c}_uj" for c in ("cpu", "dram", "gpu"))


@query("interval_energy_prorated", f"""with {T} {RUNS}, o as (select *, greatest(0, least(end_us, (slot + 1) * 3600000000) - greatest(start_us, slot * 3600000000)) o
 from r join t using (node_id)) select r.run_id, r.node_id, coalesce(n_slots, 0) n_slots, cpu_uj, dram_uj, gpu_uj
 from r left join (select run_id, count(*) n_slots {_PRO} from o where o > 0 group by all) using (run_id)""")
def interval_energy_prorated(spark, d):
    return E.interval_energy(tuples(spark, d), runs(spark, d), edges="prorated")


@query("interval_energy_prefix", f"""with {T} {RUNS} select run_id, r.node_id, coalesce(sum(cpu_uj), 0)::bigint cpu_uj, coalesce(sum(dram_uj), 0)::bigint dram_uj, coalesce(sum(gpu_uj), 0)::bigint gpu_uj
 from r left join t on r.node_id = t.node_id and slot * 3600000000 >= start_us and slot * 3600000000 < end_us
 group by all""")
def interval_energy_prefix(spark, d):
    return E.interval_energy_prefix(tuples(spark, d), runs(spark, d))


@query("cluster_series", f"with {T} select slot, sum(cpu_uj)::bigint cpu_uj, sum(dram_uj)::bigint dram_uj, sum(gpu_uj)::bigint gpu_uj from t group by all")
def cluster_series(spark, d):
    return E.cluster_series(tuples(spark, d))


_IDLE = ", i as (select node_id, component, list_sort(list(e))[floor((count(*) - 1) * 0.05)::bigint + 1] idle_uj from l group by all)"


@query("idle_baseline", f"with {LONG} {_IDLE} select * from i")
def idle_baseline(spark, d):
    return E.idle_baseline(tuples(spark, d))


@query("usage_energy", f"""with {LONG} {_IDLE} select node_id, component, sum(e)::bigint total_uj, (idle_uj * count(*))::bigint idle_total_uj, (sum(e) - idle_uj * count(*))::bigint raw_usage_uj, greatest(sum(e) - idle_uj * count(*), 0)::bigint usage_uj
 from l join i using (node_id, component) group by node_id, component, idle_uj""")
def usage_energy(spark, d):
    rows = tuples(spark, d)
    return E.usage_energy(rows, E.idle_baseline(rows))


@query("epoch_attribution", f"""with {T}, m as (select (user_id % 4)::int node_id, epoch_us(ts) start_us, lead(epoch_us(ts)) over (partition by user_id % 4
 order by ts, event_id) end_us, event_id run_id from events where event_type = 'error') select run_id, m.node_id, count(slot) n_slots, sum(cpu_uj)::bigint cpu_uj, sum(dram_uj)::bigint dram_uj, sum(gpu_uj)::bigint gpu_uj
 from m left join t on m.node_id = t.node_id and slot * 3600000000 >= start_us and slot * 3600000000 < end_us
 where end_us is not null group by all""")
def epoch_attribution(spark, d):
    """Marks of the run log (error events) cut each node's time; energy between successive marks."""
    e = read(spark, d, "events").where("event_type = 'error'").select((F.col("user_id") % 4).cast("int").alias("node_id"), F.col("event_id").alias("run_id"), micros(F.col("ts")).alias("start_us"))
    spans = e.withColumn("end_us", F.lead("start_us").over(W.partitionBy("node_id").orderBy("start_us", "run_id"))).where("end_us IS NOT NULL")
    return E.interval_energy(tuples(spark, d), spans)


@query("clock_offset", f"with {S} select node_id, (epoch_us(ts) + node_id::bigint * 1800000000) // 3600000000 slot, count(*) n from samples group by all")
def clock_offset(spark, d):
    shift = spark.createDataFrame([(n, n * 1_800_000_000) for n in range(4)], "node_id int, offset_us long")
    return E.align(samples(spark, d), offsets=shift).groupBy("node_id", "slot").agg(F.count("*").alias("n"))


@query("trace_quality", f"""with {T} select node_id, count(*) n_slots, count(*) filter (cpu_uj_filled) cpu_uj_filled, count(*) filter (dram_uj_filled) dram_uj_filled, count(*) filter (gpu_uj_filled) gpu_uj_filled, max(cpu_uj) peak_cpu_uj, list(slot
 order by cpu_uj desc nulls last, slot)[1] peak_slot, (sum(cpu_uj) // count(cpu_uj))::bigint mean_cpu_uj
 from t group by all""")
def trace_quality(spark, d):
    return E.trace_quality(tuples(spark, d))


@query("asof_power", f"""with {S}, m as (select event_id, (user_id % 4)::int node_id, ts from events where event_type = 'error'),
 c as (select node_id, ts, power_cw from samples where component = 'cpu') select event_id, m.node_id, power_cw
 from m asof left join c on m.node_id = c.node_id and m.ts >= c.ts""")
def asof_power(spark, d):
    marks = read(spark, d, "events").where("event_type = 'error'").select("event_id", (F.col("user_id") % 4).cast("int").alias("node_id"), "ts")
    return E.as_of(marks, samples(spark, d).where("component = 'cpu'").select("node_id", "ts", "power_cw"), "node_id", "ts", "power_cw").select("event_id", "node_id", "power_cw")


@query("union_local_stores", f"with {T} select node_id, count(*) n, sum(cpu_uj)::bigint cpu_uj, sum(dram_uj)::bigint dram_uj, sum(gpu_uj)::bigint gpu_uj from t group by all")
def union_local_stores(spark, d):
    """The central store as the union of the nodes' own ones."""
    rows = tuples(spark, d)
    store = rows.where("node_id = 0")
    for n in (1, 2, 3):
        store = store.unionByName(rows.where(F.col("node_id") == n))
    return store.groupBy("node_id").agg(F.count("*").alias("n"), *(F.sum(c).alias(c) for c in E.PARTS))


@query("energy_rollup_node_day", f"""with {LONG} select node_id, slot // 24 as day, component, sum(e)::bigint energy_uj, grouping(node_id, slot // 24, component)::bigint level
 from l group by rollup (node_id, slot // 24, component)""")
def energy_rollup_node_day(spark, d):
    return E.long_form(tuples(spark, d)).withColumn("day", div(F.col("slot"), 24)).rollup("node_id", "day", "component").agg(F.sum("energy_uj").alias("energy_uj"), F.grouping_id().alias("level"))


@query("pivot_components", f"""with {C} select node_id, slot, sum(e) filter (component = 'cpu')::bigint cpu, sum(e) filter (component = 'dram')::bigint dram, sum(e) filter (component = 'gpu')::bigint gpu
 from c group by all""")
def pivot_components(spark, d):
    return E.channel_energy(E.align(samples(spark, d))).groupBy("node_id", "slot").pivot("component", ["cpu", "dram", "gpu"]).agg(F.sum("energy_uj"))


@query("unpivot_components", f"with {LONG} select node_id, slot, component, e energy_uj from l")
def unpivot_components(spark, d):
    return E.long_form(tuples(spark, d))


@query("topk_slots", f"with {T} select node_id, slot, cpu_uj, k from (select *, row_number() over (partition by node_id order by cpu_uj desc, slot) k from t where cpu_uj is not null) where k <= 5")
def topk_slots(spark, d):
    k = F.row_number().over(W.partitionBy("node_id").orderBy(F.desc("cpu_uj"), "slot"))
    return tuples(spark, d).where("cpu_uj IS NOT NULL").withColumn("k", k).where("k <= 5").select("node_id", "slot", "cpu_uj", F.col("k").cast("long").alias("k"))


@query("range_frame_power", f"with {T} select node_id, slot, sum(cpu_uj) over (partition by node_id order by slot range between 3 preceding and current row)::bigint last4_uj from t")
def range_frame_power(spark, d):
    return tuples(spark, d).select("node_id", "slot", F.sum("cpu_uj").over(W.partitionBy("node_id").orderBy("slot").rangeBetween(-3, 0)).alias("last4_uj"))


@query("rank_nodes", f"""with {LONG} select *, rank() over (partition by component order by total_uj desc) place, dense_rank() over (partition by component
 order by total_uj desc) dense_place from (select node_id, component, sum(e)::bigint total_uj
 from l group by all)""")
def rank_nodes(spark, d):
    w = W.partitionBy("component").orderBy(F.desc("total_uj"))
    return E.long_form(tuples(spark, d)).groupBy("node_id", "component").agg(F.sum("energy_uj").alias("total_uj")).select("*", F.rank().over(w).cast("long").alias("place"), F.dense_rank().over(w).cast("long").alias("dense_place"))


@query("component_map", f"""with {LONG} select node_id, string_agg(component || '=' || total, ';' order by component) totals
 from (select node_id, component, sum(e)::bigint total from l group by all) group by all""")
def component_map(spark, d):
    by = E.long_form(tuples(spark, d)).groupBy("node_id", "component").agg(F.sum("energy_uj").alias("total"))
    m = by.groupBy("node_id").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("component", "total")))).alias("m"))
    return m.select("node_id", F.array_join(F.transform(F.array_sort(F.map_keys("m")), lambda k: F.concat(k, F.lit("="), F.element_at("m", k).cast("string"))), ";").alias("totals"))


@query("props_json_k", "select (props->>'$.k')::int k, count(*) n, floor(sum(floor(value * 100 + 0.5)))::bigint total_cw from events group by all")
def props_json_k(spark, d):
    return read(spark, d, "events").groupBy(F.from_json("props", "k int")["k"].alias("k")).agg(F.count("*").alias("n"), F.sum(F.floor(F.col("value") * 100 + 0.5)).alias("total_cw"))


@query("scan_events", """select event_type, count(*) n, min(event_id) first_id, max(event_id) last_id from events where ts >= timestamp '2024-01-10' and ts < timestamp '2024-01-20' and event_type in ('view', 'click') and event_id between 100 and 1000000
 group by all""")
def scan_events(spark, d):
    e = read(spark, d, "events").where("ts >= TIMESTAMP_NTZ '2024-01-10' AND ts < TIMESTAMP_NTZ '2024-01-20' AND event_type IN ('view', 'click') AND event_id BETWEEN 100 AND 1000000")
    return e.groupBy("event_type").agg(F.count("*").alias("n"), F.min("event_id").alias("first_id"), F.max("event_id").alias("last_id"))


@query("mean_power_stats", f"""with {S} select component, count(*) n, floor(avg(power_cw) * 1e6 + 0.5) / 1e6 mean_cw, floor(quantile_cont(power_cw, 0.5) * 1e6 + 0.5) / 1e6 median_cw, count(distinct node_id) nodes
 from samples group by all""")
def mean_power_stats(spark, d):
    return samples(spark, d).groupBy("component").agg(F.count("*").alias("n"), rounded(F.avg("power_cw")).alias("mean_cw"), rounded(F.percentile("power_cw", 0.5)).alias("median_cw"), F.countDistinct("node_id").alias("nodes"))


@query("filled_share", f"with {T} select node_id, floor(count(*) filter (cpu_uj_filled)::double / count(*)::double * 1e6 + 0.5) / 1e6 share from t group by all")
def filled_share(spark, d):
    return tuples(spark, d).groupBy("node_id").agg(ratio(F.count(F.when(F.col("cpu_uj_filled"), 1)), F.count("*")).alias("share"))


#: A counter of so few bits wraps often.
MODULUS = 1 << 17


@query("counter_wraps", f"with {S} select node_id, component, device, (count(*) - 1) n, (sum(power_cw) - first(power_cw order by ts))::bigint total from samples group by all")
def counter_wraps(spark, d):
    """Readings of cumulative counters that wrap, turned back into what was added: equal to the samples they were made of."""
    w = W.partitionBy("node_id", "component", "device").orderBy("ts").rowsBetween(W.unboundedPreceding, 0)
    counters = samples(spark, d).select("node_id", "component", "device", "ts", F.pmod(F.sum("power_cw").over(w), F.lit(MODULUS)).alias("counter"))
    found = E.counter_deltas(counters, MODULUS)
    return found.groupBy("node_id", "component", "device").agg(F.count("delta").alias("n"), F.coalesce(F.sum("delta"), F.lit(0)).alias("total"))
