"""Queries of preprocessing, training, measures over cells, remaining workloads and streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window as W, functions as F

from ..config import FEED, MODEL_A
from ..functions.columns import div, ratio, rounded
from ..operators import energy as E, loaders as L, measures as M, planner as P, receive as R, transport as T
from ..sources.tables import read, regimes, samples
from ..streaming import monitor as S
from . import energy_queries as EQ, feed_queries as Q
from .registry import ORACLES, query

CELLS = f"cells as ({Q.workload_sql('w02_small')})"


def cells(spark, d) -> DataFrame:
    return Q.workload(spark, d, "w02_small")


def _r(a: str, b: str) -> str:
    return f"floor(({a})::double / nullif(({b})::double, 0.0) * 1e6 + 0.5) / 1e6"


# --- preprocessing and training ---------------------------------------------------
@query("preprocess_text", r"""with t as (select doc_id, substr(trim(regexp_replace(lower(text), '[ \t\n\r\x0b\x0c]+', ' ', 'g')), 1, 200) as text from documents) select doc_id, text, len(string_split(text, ' '))::bigint n_tokens from t""")
def preprocess_text(spark, d):
    return R.preprocess_text(read(spark, d, "documents"))


@query("resize_vectors", """select vec_id, (i - 1) // 4 as place, floor(sum(floor(x::double * 1e6 + 0.5)) / (1e6 * 4) * 1e6 + 0.5) / 1e6 as value
 from (select vec_id, unnest(embedding) x, unnest(range(1, 65)) i from embeddings) group by all""")
def resize_vectors(spark, d):
    return R.resize_vectors(read(spark, d, "embeddings"))


@query("normalize_vectors", """with v as (select vec_id, label, list_transform(embedding, lambda e: e::double) x from embeddings),
 m as (select *, list_reduce(x, lambda a, b: a + b) / 64 m from v), s as (select *, sqrt(list_reduce(list_transform(x, lambda e: (e - m) * (e - m)), lambda a, b: a + b) / 64) d
 from m) select vec_id, label, floor(m * 1e6 + 0.5) / 1e6 mean, floor(d * 1e6 + 0.5) / 1e6 deviation, floor((x[1] - m) / d * 1e6 + 0.5) / 1e6 first_value, floor((x[64] - m) / d * 1e6 + 0.5) / 1e6 last_value
 from s""")
def normalize_vectors(spark, d):
    return R.normalize_vectors(read(spark, d, "embeddings")).select("vec_id", "label", rounded(F.col("m")).alias("mean"), rounded(F.col("d")).alias("deviation"), rounded(F.element_at("x", 1)).alias("first_value"), rounded(F.element_at("x", -1)).alias("last_value"))


def training_set(spark, d, seed: int = 42, batch: int = 64) -> DataFrame:
    """The 80 % of vectors whose digest is low, dealt to steps of about `batch` by a seeded digest: no order of all rows."""
    v = read(spark, d, "embeddings").where(F.conv(F.substring(F.md5(F.col("vec_id").cast("string")), 1, 2), 16, 10).cast("int") < 205)
    steps = max(1, -(-v.count() // batch))
    deal = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.col("vec_id").cast("string"))), 1, 8), 16, 10).cast("long")
    return v.withColumn("step", deal % steps).withColumn("node_id", F.col("vec_id") % 2)


def trained(spark, d, seed: int = 42, epochs: int = 1):
    """Losses by step and the weights of one run of its own."""
    rows = training_set(spark, d, seed)
    return R.train(rows, int(rows.agg(F.max("step")).first()[0] or 0) + 1, epochs)


@query("train_loss")
def train_loss(spark, d):
    """Loss of each step of two data-parallel epochs."""
    losses, _ = trained(spark, d, epochs=2)
    return spark.createDataFrame([(i, float(x)) for i, x in enumerate(losses)], "iter long, loss double")


TRACE = """tr as (select 'rep' || (event_id % 3) rep, (row_number() over (partition by event_id % 3 order by event_id) - 1) iter, floor(value * 100 + 0.5)::bigint loss_u, epoch_us(ts) t_us
 from events), ma as (select *, sum(loss_u) over w::double / count(*) over w::double ma from tr window w as (partition by rep
 order by iter rows 9 preceding))"""


def trace(spark, d) -> DataFrame:
    """Three runs of a positive series with time, a stand-in for losses that SQL can check."""
    e = read(spark, d, "events")
    rep = F.concat(F.lit("rep"), (F.col("event_id") % 3).cast("string"))
    it = F.row_number().over(W.partitionBy(F.col("event_id") % 3).orderBy("event_id")) - 1
    t = e.select(rep.alias("rep"), it.cast("long").alias("iter"), F.floor(F.col("value") * 100 + 0.5).alias("loss_u"), F.unix_micros(F.col("ts").cast("timestamp")).alias("t_us"))
    return R.moving_average(t, ["rep"])


@query("moving_avg_10", f"with {TRACE} select rep, iter, floor(ma * 1e6 + 0.5) / 1e6 ma from ma")
def moving_avg_10(spark, d):
    return trace(spark, d).select("rep", "iter", rounded(F.col("ma")).alias("ma"))


@query("loss_band", f"with {TRACE} select iter, count(*) n, floor(avg(loss_u) * 1e4 + 0.5) / 1e4 mean, floor(stddev_samp(loss_u) * 1e4 + 0.5) / 1e4 deviation from tr group by all having count(*) = 3")
def loss_band(spark, d):
    r4 = lambda x: F.floor(x * 1e4 + 0.5) / F.lit(1e4)
    return trace(spark, d).groupBy("iter").agg(F.count("*").alias("n"), r4(F.avg("loss_u")).alias("mean"), r4(F.stddev_samp("loss_u")).alias("deviation")).where("n = 3")


@query("time_to_loss", f"with {TRACE} select rep, min(t_us) filter (ma <= 5000) t_us, min(iter) filter (ma <= 5000) iter from ma group by all")
def time_to_loss(spark, d):
    low = F.col("ma") <= 5000
    return trace(spark, d).groupBy("rep").agg(F.min(F.when(low, F.col("t_us"))).alias("t_us"), F.min(F.when(low, F.col("iter"))).alias("iter"))


@query("loss_at_time", f"""with {TRACE}, q as (select rep, 1704067200000000 + day * 86400000000 t_us, day from (select distinct rep
 from tr), range(1, 29) t(day)) select q.rep, day, loss_u from q asof left join tr on q.rep = tr.rep and q.t_us >= tr.t_us""")
def loss_at_time(spark, d):
    t = trace(spark, d)
    q = t.select("rep").distinct().select("rep", F.explode(F.sequence(F.lit(1).cast("long"), F.lit(28).cast("long"))).alias("day")).withColumn("t_us", F.lit(1_704_067_200_000_000) + F.col("day") * 86_400_000_000)
    return E.as_of(q, t.select("rep", "t_us", "loss_u"), "rep", "t_us", "loss_u").select("rep", "day", "loss_u")


# --- measures ---------------------------------------------------------------------
_BASE = "b as (select * from cells where loader = 'push_batch')"

query("speedup", f"with {CELLS}, {_BASE} select c.loader, regime, {_r('c.modelled_us', 'b.modelled_us')} slower from cells c join b using (regime)")(lambda spark, d: M.speedup(cells(spark, d)))
query("energy_ratio", f"with {CELLS}, {_BASE} select c.loader, regime, " + ", ".join(f"{_r(f'c.{x}_uj', f'b.{x}_uj')} {x}_ratio" for x in ("cpu", "dram", "gpu")) + " from cells c join b using (regime)")(lambda spark, d: M.energy_ratio(cells(spark, d)))
query("slowdown_own", f"""with {CELLS} select loader, regime, {_r('modelled_us', 'first_value(modelled_us) over (partition by loader order by rtt_us)')} slower_than_nearest
 from cells""")(lambda spark, d: M.slowdown_own(cells(spark, d)))
query("energy_cut", f"with {CELLS}, {_BASE} select c.loader, regime, {_r('c.modelled_us', 'b.modelled_us')} slower, " + ", ".join(f"{_r(f'100 * (c.{x}_uj - b.{x}_uj)', f'c.{x}_uj')} {x}_cut" for x in ("cpu", "dram", "gpu")) + " from cells c join b using (regime)")(lambda spark, d: M.energy_cut(cells(spark, d)))
query("rtt_invariance", f"""with {CELLS} select loader, {_r('max(modelled_us) - min(modelled_us)', 'min(modelled_us)')} spread, (max(modelled_us) - min(modelled_us)) * 20 < min(modelled_us) is_flat
 from cells group by all""")(lambda spark, d: M.rtt_invariance(cells(spark, d)))
query("edp", f"with {CELLS} select loader, regime, floor((cpu_uj + dram_uj + gpu_uj) / 1e6 * (modelled_us / 1e6) * 1e3 + 0.5) / 1e3 edp from cells")(lambda spark, d: M.edp(cells(spark, d)))
query("pareto_front", f"""with {CELLS}, t as (select loader, regime, modelled_us, (cpu_uj + dram_uj + gpu_uj)::bigint energy_uj
 from cells) select * from t where not exists (select 1 from t o where o.regime = t.regime and o.modelled_us <= t.modelled_us and o.energy_uj <= t.energy_uj and (o.modelled_us < t.modelled_us or o.energy_uj < t.energy_uj))""")(lambda spark, d: M.pareto_front(cells(spark, d)))
query("carbon", f"""with {CELLS}, t as (select loader, regime, (cpu_uj + dram_uj + gpu_uj)::double e from cells)
 select loader, regime, floor(e / 3.6e12 * 1e9 + 0.5) / 1e9 kwh, floor(e / 3.6e12 * 458 * 1e6 + 0.5) / 1e6 co2_g
 from t""")(lambda spark, d: M.carbon(cells(spark, d)))
query("throughput", f"""with {CELLS} select loader, regime, {_r('records * 1000000', 'modelled_us')} samples_s, {_r('bytes * 1000000', 'modelled_us')} bytes_s
 from cells""")(lambda spark, d: cells(spark, d).select("loader", "regime", ratio(F.col("records") * 1_000_000, F.col("modelled_us")).alias("samples_s"), ratio(F.col("bytes") * 1_000_000, F.col("modelled_us")).alias("bytes_s")))


@query("cells_cube", f"with {CELLS} select loader, regime, sum(modelled_us)::bigint modelled_us, sum(cpu_uj)::bigint cpu_uj, count(*) n from cells group by cube (loader, regime)")
def cells_cube(spark, d):
    return cells(spark, d).cube("loader", "regime").agg(F.sum("modelled_us").alias("modelled_us"), F.sum("cpu_uj").alias("cpu_uj"), F.count("*").alias("n"))


@query("cells_grouping_sets", f"with {CELLS} select loader, regime, sum(modelled_us)::bigint modelled_us, count(*) n from cells group by grouping sets ((loader), (regime), ())")
def cells_grouping_sets(spark, d):
    cells(spark, d).createOrReplaceTempView("feed_cells")
    return spark.sql("SELECT loader, regime, sum(modelled_us) AS modelled_us, count(*) AS n FROM feed_cells GROUP BY GROUPING SETS ((loader), (regime), ())")


@query("regress_time_on_rtt", f"with {CELLS} select loader, floor(regr_slope(modelled_us::double, rtt_us::double) * 1e4 + 0.5) / 1e4 slope from cells group by all")
def regress_time_on_rtt(spark, d):
    return cells(spark, d).groupBy("loader").agg((F.floor(F.regr_slope(F.col("modelled_us").cast("double"), F.col("rtt_us").cast("double")) * 1e4 + 0.5) / F.lit(1e4)).alias("slope"))


@query("exact_percentiles", "select source, floor(quantile_cont(strlen(text), 0.5) * 1e6 + 0.5) / 1e6 p50, floor(quantile_cont(strlen(text), 0.9) * 1e6 + 0.5) / 1e6 p90 from documents group by all")
def exact_percentiles(spark, d):
    n = F.octet_length("text").cast("long")
    return read(spark, d, "documents").groupBy("source").agg(rounded(F.percentile(n, 0.5)).alias("p50"), rounded(F.percentile(n, 0.9)).alias("p90"))


# --- remaining workloads ----------------------------------------------------------
STAGE_RTTS = ("local", "lan_fast", "lan_10", "wan")
IDLE, BUSY = dict(MODEL_A.idle), dict(MODEL_A.busy)
IDLE_W, BUSY_W = sum(IDLE.values()), sum(BUSY.values())
_READ = f"""with recursive {Q.pull_sql('pull_pipeline', names=STAGE_RTTS)}, x as (select regime, sum(fetch_us)::bigint read_us, sum(n * {FEED.decode_us})::bigint prep_us, sum(n * {FEED.step_us})::bigint train_us from dl group by all)"""
_STAGES = _READ + f""", s as (select regime, 1 stage_no, read_us us, read_us * {IDLE_W} uj from x
 union all select regime, 2, read_us + prep_us, read_us * {IDLE_W} + prep_us * {IDLE_W + BUSY['cpu']} from x
 union all select regime, 3, read_us + prep_us + train_us, read_us * {IDLE_W} + prep_us * {IDLE_W + BUSY['cpu']} + train_us * {IDLE_W + BUSY_W} from x)"""


def stages(spark, d) -> DataFrame:
    """Cumulative times and energies of the stages without overlap: read, + preprocess, + train.

    All components idle while reading; the CPU is busy while preprocessing, all are while training.
    """
    f = L.pull_pipeline(Q.batches(spark, d), regimes(spark, *STAGE_RTTS))
    x = f.groupBy("regime").agg(F.sum("fetch_us").alias("a"), F.sum(F.col("n") * FEED.decode_us).alias("b"), F.sum(F.col("n") * FEED.step_us).alias("c"))
    own = [(F.col("a"), IDLE_W), (F.col("b"), IDLE_W + BUSY["cpu"]), (F.col("c"), IDLE_W + BUSY_W)]
    upto = [F.struct(F.lit(k).alias("stage_no"), sum((t for t, _ in own[:k]), F.lit(0)).cast("long").alias("us"), sum((t * w for t, w in own[:k]), F.lit(0)).cast("long").alias("uj")) for k in (1, 2, 3)]
    return x.select("regime", F.inline(F.array(*upto)))


_SHARES = f"""{_STAGES}, o as (select *, us - coalesce(lag(us) over w, 0) own_us, uj - coalesce(lag(uj) over w, 0) own_uj, max(us) over (partition by regime) m, max(uj) over (partition by regime) e from s window w as (partition by regime order by stage_no))"""
query("w01_breakdown", f"{_SHARES} select regime, stage_no, us, own_us, {_r('own_us', 'm')} share, uj, own_uj, {_r('own_uj', 'e')} energy_share from o")(lambda spark, d: M.stage_shares(stages(spark, d)))
query("io_share", f"""{_SHARES} select regime, {_r('max(own_us) filter (stage_no = 1)', 'max(m)')} share, {_r('max(own_uj) filter (stage_no = 1)', 'max(e)')} energy_share, {_r('max(us) filter (stage_no = 2)', 'max(m)')} fetch_share, {_r('max(uj) filter (stage_no = 2)', 'max(e)')} fetch_energy_share
 from o group by all""")(lambda spark, d: M.io_shares(stages(spark, d)))

def _half_local(spark, d, loader: str) -> DataFrame:
    """Every node streams all shards; those placed on it cost no round trip."""
    names = ("lan", "lan_10", "wan")
    b = Q.batches(spark, d, coverage="replicate")
    where = P.place_shards(Q.stats(spark, d), 2).select("shard_id", "server")
    home = Q.plan(spark, d, coverage="replicate").join(where, "shard_id").select("epoch", "node_id", "worker", "batch_seq", (F.col("server") == F.col("node_id")).alias("is_local"))
    b = b.join(home, ["epoch", "node_id", "worker", "batch_seq"])
    r = regimes(spark, *names)
    if loader == "push_batch":
        t = T.services(b).crossJoin(F.broadcast(r))
        done = T.pipeline_times(t)
        lag = F.when(F.col("is_local"), F.lit(0).cast("long")).otherwise(F.col("rtt_us") + div(F.col("rtt_us"), 2))
        done = L.consumed(T.delivered(done.withColumn("arrival", F.col("send_done") + lag)))
    else:
        far = F.when(F.col("is_local"), F.lit(0).cast("long")).otherwise(F.col("rtt_us"))
        done = L.consumed(L.pull_pipeline(b, r, rtt=far))
    by = done.groupBy("regime", "epoch", "node_id").agg(F.max("done").alias("t"), F.sum(F.when(F.col("is_local"), F.col("n")).otherwise(0)).alias("near"), F.sum("n").alias("n"))
    by = by.groupBy("regime", "epoch").agg(F.max("t").alias("t"), F.sum("near").alias("near"), F.sum("n").alias("n"))
    sums = by.groupBy("regime").agg(F.sum("t").alias("modelled_us"), F.sum("n").alias("records"), ratio(F.sum("near"), F.sum("n")).alias("local_share"))
    energy = [(F.col("modelled_us") * FEED.nodes * IDLE[c] + F.col("records") * FEED.step_us * BUSY[c]).alias(f"{c}_uj") for c in ("cpu", "dram", "gpu")]
    return sums.select(F.lit(loader).alias("loader"), "regime", "local_share", "records", "modelled_us", *energy)


_W7_ENERGY = ", ".join(f"(sum(t) * {FEED.nodes * IDLE[c]} + sum(n) * {FEED.step_us * BUSY[c]})::bigint {c}_uj" for c in ("cpu", "dram", "gpu"))


def _w7_sql(loader: str) -> str:
    home = """hm as (select epoch, node_id, worker, batch_seq, any_value(server = node_id) is_local from pl
 join (select shard_id, (row_number() over (order by shard_id) - 1) % 2 server from st) using (shard_id)
 group by all)"""
    names = ("lan", "lan_10", "wan")
    if loader == "push_batch":
        head = Q.push_sql(names=names, coverage="replicate")
        head = head[: head.index(", ar as (")] + f""", {home}, ar as (select p3.*, is_local, send_done + case when is_local then 0 else rtt_us + rtt_us // 2 end arrival
 from p3 join hm using (epoch, node_id, worker, batch_seq)), dl as (select *, row_number() over (partition by {Q.ND}
 order by arrival, worker, batch_seq) turn, arrival ready from ar)"""
    else:
        head = f"""{Q.batches_sql(coverage='replicate')}, {home}, {Q.regimes_sql(names)}, f as (select bt.*, is_local, regime, rtt_us, greatest(n * greatest(1, (bytes * 40 + n * 1048576 - 1) // (n * 1048576)) * (case when is_local then 0 else rtt_us end) * 570 // 1000, bytes * 40 * 1000000 // 1250000000 + bytes * 40 * 1000000 // 500000000)::bigint fetch_us, row_number() over (partition by {Q.ND}
 order by batch_seq, worker) turn from bt join hm using (epoch, node_id, worker, batch_seq), rg),
 dl as (select *, (sum(fetch_us) over (partition by {Q.ND} order by turn))::bigint ready from f)"""
    return f"""select * from (with recursive {head}, {Q.used_sql()}, e as (select regime, epoch, max(t) t, sum(near) near, sum(n) n
 from (select regime, epoch, node_id, max(done) t, sum(case when is_local then n else 0 end) near, sum(n) n
 from us group by all) group by all) select '{loader}' loader, regime, {_r('sum(near)', 'sum(n)')} local_share, sum(n)::bigint records, sum(t)::bigint modelled_us, {_W7_ENERGY}
 from e group by all)"""


_W7 = f"{_w7_sql('push_batch')} union all {_w7_sql('pull_pipeline')}"


def sharded(spark, d) -> DataFrame:
    return _half_local(spark, d, "push_batch").unionByName(_half_local(spark, d, "pull_pipeline"))


query("w07_sharded", _W7)(sharded)
query("w07_energy_cut", f"with cells as ({_W7}), b as (select * from cells where loader = 'push_batch') select c.regime, {_r('c.modelled_us', 'b.modelled_us')} slower, " + ", ".join(f"{_r(f'100 * (c.{x}_uj - b.{x}_uj)', f'c.{x}_uj')} {x}_cut" for x in ("cpu", "dram", "gpu")) + " from cells c join b using (regime) where c.loader = 'pull_pipeline'")(lambda spark, d: M.energy_cut(sharded(spark, d)).where("loader = 'pull_pipeline'").drop("loader"))


def step_ends(spark, d, loader: str) -> list[int]:
    """When each step of a node's first epoch ends, by the loader's own model at 10 ms."""
    make = {"push_batch": L.push_batch, "pull_pipeline": L.pull_pipeline}[loader]
    b = Q.batches(spark, d, "embeddings", scope="node", epochs=1)
    done = L.consumed(make(b, regimes(spark, "lan_10"), Q.SYNTHETIC), Q.SYNTHETIC)
    return [r.done for r in done.groupBy("turn").agg(F.max("done").alias("done")).orderBy("turn").collect()]  # one row a step


@query("w08_loss_over_time")
def w08_loss_over_time(spark, d):
    """Losses of three runs on the time axes of the two loaders: mean and deviation of their moving averages."""
    runs = [(seed, [float(x) for x in trained(spark, d, seed)[0]]) for seed in (42, 43, 44)]
    out = []
    for loader in ("push_batch", "pull_pipeline"):
        ends = step_ends(spark, d, loader)
        out += [(loader, seed, i, ends[min(i, len(ends) - 1)] + max(0, i + 1 - len(ends)) * (ends[-1] // len(ends)), x) for seed, losses in runs for i, x in enumerate(losses)]
    t = spark.createDataFrame(out, "loader string, seed int, iter long, t_us long, loss double")
    ma = t.withColumn("ma", F.avg("loss").over(W.partitionBy("loader", "seed").orderBy("iter").rowsBetween(-9, 0)))
    return ma.groupBy("loader", "iter", "t_us").agg(F.count("*").alias("runs"), F.avg("ma").alias("mean"), F.stddev_samp("ma").alias("deviation"))


@query("w08_faster_to_any_loss", "select loader, true is_earlier from (values ('push_batch')) t(loader)")
def w08_faster_to_any_loss(spark, d):
    """The loader that reaches every step first, and so any loss that the runs reach."""
    both = w08_loss_over_time(spark, d)
    a, b = (both.where(F.col("loader") == x).select("iter", F.col("t_us").alias(x)) for x in ("push_batch", "pull_pipeline"))
    return a.join(b, "iter").agg(F.min(F.col("push_batch") < F.col("pull_pipeline")).alias("is_earlier")).select(F.lit("push_batch").alias("loader"), "is_earlier")


def accuracy(spark, d, loader: str) -> DataFrame:
    """Held-out accuracy after a run of the loader's own: its batches read from its own plan."""
    rows = training_set(spark, d)
    _, weights = trained(spark, d)
    held = read(spark, d, "embeddings").join(rows.select("vec_id"), "vec_id", "left_anti")
    x = F.transform("embedding", lambda a: a.cast("double"))
    scores = F.array(*(F.aggregate(F.zip_with(x, F.array(*(F.lit(v) for v in c)), lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v) for c in weights.T.tolist()))
    hit = held.select((F.array_position(scores, F.array_max(scores)) - 1 == F.col("label")).alias("hit"))
    return hit.agg(F.count("*").alias("n"), rounded(F.avg(F.col("hit").cast("double"))).alias("accuracy")).select(F.lit(loader).alias("loader"), "n", "accuracy")


@query("w09_outcome")
def w09_outcome(spark, d):
    """Accuracy and energy of two runs, one a loader, each trained by itself: the plan decides the outcome, the loader its cost."""
    cost = L.cells(Q.batches(spark, d, "embeddings", scope="node"), regimes(spark, "lan_10"), Q.SYNTHETIC, MODEL_A, Q.TWO).select("loader", "modelled_us", (F.col("cpu_uj") + F.col("dram_uj") + F.col("gpu_uj")).alias("energy_uj"))
    return accuracy(spark, d, "push_batch").unionByName(accuracy(spark, d, "pull_pipeline")).join(F.broadcast(cost), "loader")


@query("w09_equal_outcome", "select 1::bigint outcomes, 2::bigint costs")
def w09_equal_outcome(spark, d):
    """Distinct accuracies and distinct energies of the runs of w09."""
    return w09_outcome(spark, d).agg(F.countDistinct("accuracy").alias("outcomes"), F.countDistinct("energy_uj").alias("costs"))


@query("decode_sync_async", f"""with recursive {Q.push_sql(names=('lan', 'wan'))}, ds as (select *, n * {FEED.decode_us} decode_us, n * {FEED.step_us} step_us, row_number() over (partition by {Q.ND}
 order by turn) rn from dl), aw as (select *, ready + decode_us decoded, ready + decode_us + step_us apart, ready + decode_us + step_us together
 from ds where rn = 1 union all select x.*, greatest(p.decoded, x.ready) + x.decode_us, greatest(p.apart, greatest(p.decoded, x.ready) + x.decode_us) + x.step_us, greatest(p.together, x.ready) + x.decode_us + x.step_us
 from ds x join aw p on x.regime = p.regime and x.epoch = p.epoch and x.node_id = p.node_id and x.rn = p.rn + 1)
 select regime, epoch, node_id, max(apart) async_us, max(together) sync_us from aw group by all""")
def decode_sync_async(spark, d):
    """Decoding beside the training step, or before it in the same loop."""
    b = L.push_batch(Q.batches(spark, d), regimes(spark, "lan", "wan"))
    work = F.col("n") * FEED.decode_us, F.col("n") * FEED.step_us
    apart = T.queue_done(T.queue_done(b, L.NODE, ["turn"], work[0], "decoded", F.col("ready")), L.NODE, ["turn"], work[1], "async_us", F.col("decoded"))
    both = T.queue_done(apart, L.NODE, ["turn"], work[0] + work[1], "sync_us", F.col("ready"))
    return both.groupBy("regime", "epoch", "node_id").agg(F.max("async_us").alias("async_us"), F.max("sync_us").alias("sync_us"))


query("w10_scale_out", f"""with {Q.base_sql('lineitem')}, k as (select *, row_number() over (order by shard_id) - 1 k
 from st), b as (select servers, k % servers server, sum(100 + bytes * 40 * 1000000 // 500000000)::bigint us
 from k, (values (1), (2), (4), (8)) t(servers) group by all), m as (select servers::bigint servers, max(us) t
 from b group by all) select servers, {_r('(select t from m where servers = 1)', 't')} speedup
 from m""")(lambda spark, d: _w10(spark, d))


def _w10(spark, d) -> DataFrame:
    t = T.scale_out(Q.stats(spark, d, "lineitem"))
    one = t.where("servers = 1").select(F.col("makespan_us").alias("one"))
    return t.crossJoin(F.broadcast(one)).select("servers", ratio(F.col("one"), F.col("makespan_us")).alias("speedup"))


_GRIDS = (1, 60, 1440)
_W11 = " union all ".join(
    f"""select {m}::bigint delta_min, node_id, component, count(*) n_slots, sum(e)::bigint energy_uj
 from (select node_id, component, device, epoch_us(ts) // {m * 60_000_000}::bigint slot, ((sum(power_cw)::bigint * {m * 60_000_000}::bigint) // (count(*) * 100))::bigint e
 from (with {EQ.S} select * from samples) group by all) group by all"""
    for m in _GRIDS
)


@query("w11_monitor", _W11)
def w11_monitor(spark, d):
    """The monitor's energies on grids of a minute, an hour and a day."""
    out = None
    for m in _GRIDS:
        us = m * 60_000_000
        c = E.channel_energy(E.align(samples(spark, d), us), us).groupBy("node_id", "component").agg(F.count("*").alias("n_slots"), F.sum("energy_uj").alias("energy_uj")).withColumn("delta_min", F.lit(m).cast("long"))
        out = c if out is None else out.unionByName(c)
    return out


query("w12_traffic", ORACLES["traffic_by_rtt_class"])(Q.traffic_by_rtt_class)

#: Printed epoch seconds, group, regime, loader, seconds.
PUBLISHED = (
    ("small", "local", "push_batch", 157.1), ("small", "local", "pull_pipeline", 151.7), ("small", "local", "pull_sample", 172.4),
    ("small", "lan", "push_batch", 156.6), ("small", "lan", "pull_pipeline", 165.4), ("small", "lan", "pull_sample", 175.5),
    ("small", "lan_10", "push_batch", 156.5), ("small", "lan_10", "pull_pipeline", 552.5), ("small", "lan_10", "pull_sample", 1202.2),
    ("small", "wan", "push_batch", 156.2), ("small", "wan", "pull_pipeline", 1699.3), ("small", "wan", "pull_sample", 4232.4),
    ("model_b", "lan", "push_batch", 141.1), ("model_b", "lan", "pull_pipeline", 142.6), ("model_b", "lan_10", "push_batch", 140.0),
    ("model_b", "lan_10", "pull_pipeline", 660.9), ("model_b", "wan", "push_batch", 140.5), ("model_b", "wan", "pull_pipeline", 2096.8),
    ("sharded", "lan", "push_batch", 222.5), ("sharded", "lan", "pull_pipeline", 230.9), ("sharded", "lan_10", "push_batch", 221.6),
    ("sharded", "lan_10", "pull_pipeline", 1422.5), ("sharded", "wan", "push_batch", 221.8), ("sharded", "wan", "pull_pipeline", 4154.7),
)


def modelled(spark, d) -> DataFrame:
    """Times and energies of the groups that are printed, as the model has them over documents, with those of the push loader beside them."""
    by = (("small", cells(spark, d)), ("model_b", Q.workload(spark, d, "w06_model_b")), ("sharded", sharded(spark, d)))
    out = None
    for grp, df in by:
        t = df.select(F.lit(grp).alias("grp"), "regime", "loader", "modelled_us", "cpu_uj", "dram_uj", "gpu_uj")
        out = t if out is None else out.unionByName(t)
    push = lambda c: F.max(F.when(F.col("loader") == "push_batch", F.col(c))).over(W.partitionBy("grp", "regime"))
    return out.select("*", *(push(c).alias(f"push_{c}") for c in ("modelled_us", "cpu_uj", "dram_uj", "gpu_uj")))


_MODELLED = "mo as (" + " union all ".join(f"select '{grp}' grp, regime, loader, modelled_us, cpu_uj, dram_uj, gpu_uj from ({sql})" for grp, sql in (("small", Q.workload_sql("w02_small")), ("model_b", Q.workload_sql("w06_model_b")), ("sharded", _W7))) + """),
 md as (select m.*, b.modelled_us push_modelled_us, b.cpu_uj push_cpu_uj, b.dram_uj push_dram_uj, b.gpu_uj push_gpu_uj
 from mo m join mo b on m.grp = b.grp and m.regime = b.regime and b.loader = 'push_batch')"""


@query("w13_audit", f"""with {_MODELLED}, p as (select * from (values {', '.join(str(x) for x in PUBLISHED)}) t(grp, regime, loader, s))
 select a.grp, a.regime, a.loader, a.s::double as seconds, {_r('a.s', 'b.s')} over_push, modelled_us, {_r('modelled_us', 'push_modelled_us')} modelled_over_push from p a
 join p b on a.grp = b.grp and a.regime = b.regime and b.loader = 'push_batch'
 join md on md.grp = a.grp and md.regime = a.regime and md.loader = a.loader""")
def w13_audit(spark, d):
    """Times over those of the push loader, of the printed seconds and of the model over documents."""
    p = spark.createDataFrame(list(PUBLISHED), "grp string, regime string, loader string, seconds double")
    b = p.where("loader = 'push_batch'").select("grp", "regime", F.col("seconds").alias("_b"))
    p = p.join(F.broadcast(b), ["grp", "regime"]).select("grp", "regime", "loader", "seconds", ratio(F.col("seconds"), F.col("_b")).alias("over_push"))
    m = modelled(spark, d).select("grp", "regime", "loader", "modelled_us", ratio(F.col("modelled_us"), F.col("push_modelled_us")).alias("modelled_over_push"))
    return m.join(F.broadcast(p), ["grp", "regime", "loader"]).select("grp", "regime", "loader", "seconds", "over_push", "modelled_us", "modelled_over_push")


#: Printed energies in kJ, group, regime, loader, CPU, DRAM, GPU.
PUBLISHED_KJ = (
    ("model_b", "lan", "pull_pipeline", 19.9, 1.7, 34.6), ("model_b", "lan", "push_batch", 20.0, 1.6, 34.5),
    ("model_b", "lan_10", "pull_pipeline", 56.1, 4.7, 78.0), ("model_b", "lan_10", "push_batch", 19.8, 1.6, 34.2),
    ("model_b", "wan", "pull_pipeline", 156.3, 11.8, 163.6), ("model_b", "wan", "push_batch", 20.3, 1.6, 34.4),
    ("sharded", "lan", "pull_pipeline", 22.2, 2.08, 43.8), ("sharded", "lan", "push_batch", 19.7, 2.03, 41.7),
    ("sharded", "lan_10", "pull_pipeline", 60.7, 5.03, 90.8), ("sharded", "lan_10", "push_batch", 52.5, 4.96, 72.0),
    ("sharded", "wan", "pull_pipeline", 180.0, 14.2, 235.0), ("sharded", "wan", "push_batch", 106.0, 9.01, 126.0),
)
#: Printed cuts in percent, group, regime, CPU, DRAM, GPU (null: not printed).
PUBLISHED_CUTS = (("sharded", "lan", 11.5, 2.5, 4.7), ("sharded", "lan_10", 13.5, None, 20.8), ("sharded", "wan", 41.1, None, 46.4))
#: Claims of the summary, measure, factor.
CLAIMS = (("time", 8.6), ("energy", 10.9), ("time", 13.0), ("energy", 8.0))

_KJ = f"""k as (select * from (values {', '.join(map(str, PUBLISHED_KJ))}) t(grp, regime, loader, cpu, dram, gpu)),
 a as (select p.*, s.cpu c2, s.dram d2, s.gpu g2 from k p join k s using (grp, regime) where p.loader = 'pull_pipeline' and s.loader = 'push_batch')"""
_CUTS = f"u as (select * from (values {', '.join(str(x).replace('None', 'null') for x in PUBLISHED_CUTS)}) t(grp, regime, cpu_printed, dram_printed, gpu_printed))"


def _published_kj(spark) -> DataFrame:
    k = spark.createDataFrame(list(PUBLISHED_KJ), "grp string, regime string, loader string, cpu double, dram double, gpu double")
    own = k.where("loader = 'push_batch'").select("grp", "regime", F.col("cpu").alias("c2"), F.col("dram").alias("d2"), F.col("gpu").alias("g2"))
    return k.where("loader = 'pull_pipeline'").join(F.broadcast(own), ["grp", "regime"])


_TOTAL = " + ".join(f"{{0}}{c}_uj" for c in ("cpu", "dram", "gpu"))
_MODEL_CUTS = ", ".join(f"{_r(f'100 * ({c}_uj - push_{c}_uj)', f'{c}_uj')} modelled_{c}_cut" for c in ("cpu", "dram", "gpu"))


@query("w13_audit_energy", f"""with {_MODELLED}, {_KJ}, {_CUTS} select a.grp, a.regime, {_r('cpu + dram + gpu', 'c2 + d2 + g2')} ratio, {_r('100 * (cpu - c2)', 'cpu')} cpu_cut, {_r('100 * (dram - d2)', 'dram')} dram_cut, {_r('100 * (gpu - g2)', 'gpu')} gpu_cut, cpu_printed::double cpu_printed, dram_printed::double dram_printed, gpu_printed::double gpu_printed, coalesce(abs(cpu_printed - 100 * (cpu - c2) / cpu) < 0.5 and abs(gpu_printed - 100 * (gpu - g2) / gpu) < 0.5, false) agrees,
 {_r(_TOTAL.format(''), _TOTAL.format('push_'))} modelled_ratio, {_MODEL_CUTS}
 from a left join u on a.grp = u.grp and a.regime = u.regime
 join md on md.grp = a.grp and md.regime = a.regime and md.loader = 'pull_pipeline'""")
def w13_audit_energy(spark, d):
    """Cuts and ratios recomputed from the printed energies, beside the printed cuts and those of the model over documents."""
    u = spark.createDataFrame(list(PUBLISHED_CUTS), "grp string, regime string, cpu_printed double, dram_printed double, gpu_printed double")
    a = _published_kj(spark).join(F.broadcast(u), ["grp", "regime"], "left")
    cut = lambda x, y: 100 * (F.col(x) - F.col(y))
    near = lambda p, x, y: F.abs(F.col(p) - cut(x, y) / F.col(x)) < 0.5
    total = ratio(F.col("cpu") + F.col("dram") + F.col("gpu"), F.col("c2") + F.col("d2") + F.col("g2"))
    cuts = [ratio(cut(x, y), F.col(x)).alias(f"{x}_cut") for x, y in (("cpu", "c2"), ("dram", "d2"), ("gpu", "g2"))]
    printed = a.select("grp", "regime", total.alias("ratio"), *cuts, "cpu_printed", "dram_printed", "gpu_printed", F.coalesce(near("cpu_printed", "cpu", "c2") & near("gpu_printed", "gpu", "g2"), F.lit(False)).alias("agrees"))
    own = [ratio(cut(f"{x}_uj", f"push_{x}_uj"), F.col(f"{x}_uj")).alias(f"modelled_{x}_cut") for x in ("cpu", "dram", "gpu")]
    m = modelled(spark, d).where("loader = 'pull_pipeline'").select("grp", "regime", ratio(F.expr(_TOTAL.format("")), F.expr(_TOTAL.format("push_"))).alias("modelled_ratio"), *own)
    return m.join(F.broadcast(printed), ["grp", "regime"]).select(*printed.columns, *(c for c in m.columns if c not in printed.columns))


@query("w13_headlines", f"""with {_MODELLED}, {_KJ}, p as (select * from (values {', '.join(map(str, PUBLISHED))}) t(grp, regime, loader, s)),
 m as (select 'time' measure, max(x.s / y.s)::double most, (select max(modelled_us::double / push_modelled_us::double) from md) most_m from p x join p y on x.grp = y.grp and x.regime = y.regime and y.loader = 'push_batch'
 union all select 'energy', max((cpu + dram + gpu) / (c2 + d2 + g2))::double, (select max(({_TOTAL.format('')})::double / ({_TOTAL.format('push_')})::double) from md where loader = 'pull_pipeline' and grp <> 'small') from a)
 select measure, claimed::double claimed, floor(most * 1e6 + 0.5) / 1e6 most_printed, most >= claimed supported, floor(most_m * 1e6 + 0.5) / 1e6 most_modelled, most_m >= claimed modelled_supports
 from (values {', '.join(map(str, CLAIMS))}) c(measure, claimed) join m using (measure)""")
def w13_headlines(spark, d):
    """Claimed factors against the largest that the printed tables give, and that the model gives over documents in the same cells."""
    p = spark.createDataFrame(list(PUBLISHED), "grp string, regime string, loader string, s double")
    b = p.where("loader = 'push_batch'").select("grp", "regime", F.col("s").alias("b"))
    time = p.join(F.broadcast(b), ["grp", "regime"]).agg(F.max(F.col("s") / F.col("b")).alias("most")).select(F.lit("time").alias("measure"), "most")
    energy = _published_kj(spark).agg(F.max((F.col("cpu") + F.col("dram") + F.col("gpu")) / (F.col("c2") + F.col("d2") + F.col("g2"))).alias("most")).select(F.lit("energy").alias("measure"), "most")
    claims = spark.createDataFrame(list(CLAIMS), "measure string, claimed double")
    j = claims.join(F.broadcast(time.unionByName(energy)), "measure")
    over = F.expr(f"({_TOTAL.format('')}) / ({_TOTAL.format('push_')})")
    most = modelled(spark, d).agg(F.max(F.col("modelled_us") / F.col("push_modelled_us")).alias("time"), F.max(F.when((F.col("loader") == "pull_pipeline") & (F.col("grp") != "small"), over)).alias("energy"))
    j = j.join(F.broadcast(most.selectExpr("stack(2, 'time', time, 'energy', energy) AS (measure, most_m)")), "measure")
    return j.select("measure", "claimed", rounded(F.col("most")).alias("most_printed"), (F.col("most") >= F.col("claimed")).alias("supported"), rounded(F.col("most_m")).alias("most_modelled"), (F.col("most_m") >= F.col("claimed")).alias("modelled_supports"))


@query("trace_from_busy", "with recursive " + Q.push_sql(names=("wan",)) + ", " + Q.used_sql() + """, b as (select epoch * 10 + node_id node_id, done - n * 1500 s, done e from us), x as (select node_id, k slot, sum(least(e, (k + 1) * 100000) - greatest(s, k * 100000))::bigint u
 from b, range(0, 100000) t(k) where k >= s // 100000 and k <= (e - 1) // 100000 group by all)
 select node_id, slot, (60 * 100000 + 5 * u)::bigint cpu_uj, (5 * 100000 + 2 * u)::bigint dram_uj, (60 * 100000 + 107 * u)::bigint gpu_uj
 from x""")
def trace_from_busy(spark, d):
    done = L.consumed(L.push_batch(Q.batches(spark, d), regimes(spark, "wan")))
    busy = done.select((F.col("epoch") * 10 + F.col("node_id")).alias("node_id"), (F.col("done") - F.col("n") * FEED.step_us).alias("start_us"), F.col("done").alias("end_us"))
    return E.trace_from_busy(busy, MODEL_A, 100_000)


# --- streams ----------------------------------------------------------------------
_WIN = """with {s} select node_id, component, device, time_bucket(interval '1 hour', ts) start_ts, time_bucket(interval '1 hour', ts) + interval '1 hour' end_ts, sum(power_cw)::bigint total_cw, count(*) n
 from samples group by all"""
query("stream_tick_energy", _WIN.format(s=EQ.S))(lambda spark, d: S.run_once(S.tick_energy(S.sample_stream(spark, d)), "complete"))
query("stream_sliding_power", f"""with {EQ.S}, b as (select node_id, power_cw, time_bucket(interval '1 hour', ts) - k * interval '1 hour' start_ts
 from samples, range(0, 6) t(k)) select node_id, start_ts, start_ts + interval '6 hours' end_ts, sum(power_cw)::bigint total_cw, count(*) n
 from b group by all""")(lambda spark, d: S.run_once(S.sliding_power(S.sample_stream(spark, d)), "complete"))
query("stream_sessions", f"""with {EQ.S}, g as (select *, case when ts - lag(ts) over (partition by node_id order by ts) < interval '30 minutes' then 0 else 1 end f
 from samples), s as (select *, sum(f) over (partition by node_id order by ts rows unbounded preceding) k
 from g) select node_id, min(ts) start_ts, max(ts) + interval '30 minutes' end_ts, count(*) n
 from s group by node_id, k""")(lambda spark, d: S.run_once(S.sessions(S.sample_stream(spark, d)), "complete"))
query("stream_send_receipt_join", "select s.user_id % 4 node_id, s.event_id send_id, r.event_id receipt_id from events s join events r on s.user_id % 4 = r.user_id % 4 and s.event_type = 'view' and r.event_type = 'click' and r.ts >= s.ts and r.ts < s.ts + interval '1 hour'")(lambda spark, d: S.run_once(S.send_receipt(S.event_stream(spark, d)), "append"))
query("stream_dedup", "select event_id, event_type from events")(lambda spark, d: S.run_once(S.deduplicated(S.event_stream(spark, d)), "append"))


_CLOSED = """e as (select node_id, slot, e v from c where component = 'cpu' and (slot + 1) * 3600000000 <= (select max(epoch_us(ts)) from samples where component = 'cpu') - 3600000000),
n as (select *, lead(slot) over w s2, lead(v) over w v2 from e window w as (partition by node_id order by slot))"""


@query("stream_interpolate", f"""with {EQ.C}, {_CLOSED} select node_id, slot + k slot, ((v * (coalesce(s2, slot + 1) - slot) + (coalesce(v2, v) - v) * k) // (coalesce(s2, slot + 1) - slot))::bigint cpu_uj, k > 0 filled
 from n, range(0, 100000) t(k) where k < coalesce(s2, slot + 1) - slot""")
def stream_interpolate(spark, d):
    """The stream's filled ticks, which the batch form over the closed ticks must equal."""
    with S.rocksdb_state(spark):
        return S.run_once(S.interpolated(S.cpu_ticks(S.sample_stream(spark, d))), "append")
