"""Catalogue queries against their DuckDB oracles, and laws of the model."""

from __future__ import annotations

import glob
import os
import random
import struct
from concurrent.futures import ThreadPoolExecutor

import duckdb
import numpy as np
import pandas as pd
import pytest

from pyspark.sql import functions as F

from batchfeed.functions.cells import cell_of, running_sums
from batchfeed.operators import energy as E, loaders as L, payload as K, planner as P, receive as R, shards as H, transport as T
from batchfeed.plans.catalog import ORACLES, QUERIES
from batchfeed.sources import framed
from batchfeed.streaming import monitor, sinks

DATA = "/root/testdata/sf0.001"


def cell(v):
    if isinstance(v, (list, np.ndarray)):
        return "[" + ",".join(map(cell, v)) + "]"
    if v is None or v is pd.NA or v is pd.NaT or (isinstance(v, float) and v != v):
        return ""
    return f"{float(v):.6f}" if isinstance(v, (int, float, np.number)) and not isinstance(v, bool) else str(v)


def rows(frame):
    frame = frame[sorted(frame.columns)]
    return sorted(tuple(map(cell, r)) for r in frame.itertuples(index=False))


@pytest.fixture(scope="module")
def tables():
    con = duckdb.connect()
    for f in glob.glob(f"{DATA}/*.parquet"):
        con.execute(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    return con


def test_every_query_has_a_callable():
    assert set(ORACLES) <= set(QUERIES) and len(QUERIES) > 100


def test_tandem_by_hand(spark):
    b = spark.createDataFrame([("r", 1, 0, 0, i, *s) for i, s in enumerate([(2, 5, 1), (1, 1, 4), (3, 2, 2)])], "regime string, epoch int, node_id int, worker int, batch_seq int, read_us long, pack_us long, send_us long")
    got = [tuple(r)[-3:] for r in T.pipeline_times(b).orderBy("batch_seq").collect()]
    assert got == [(2, 7, 8), (3, 8, 12), (6, 10, 14)]


def test_delivery_by_hand(spark):
    d = spark.createDataFrame([("r", 1, 0, 0, i, a) for i, a in enumerate([5, 3, 9, 4])], "regime string, epoch int, node_id int, worker int, batch_seq int, arrival long")
    assert [r.ready for r in T.delivered(d, "in_order").orderBy("batch_seq").collect()] == [5, 5, 9, 9]
    assert [r.ready for r in T.delivered(d, "arrival").orderBy("turn").collect()] == [3, 4, 5, 9]


@pytest.mark.parametrize("scope,want", [("shard", 6), ("node", 5)])
def test_batch_counts_by_hand(spark, scope, want):
    stats = spark.createDataFrame([(f"s{i}", n) for i, n in enumerate([0, 1, 31, 32, 65])], "shard_id string, n long")
    work = P.assign_workers(P.assign_nodes(P.shuffle_shards(stats, 1), 1), 1)
    plan = P.batch_plan(work, 32, scope)
    assert plan.select("node_id", "worker", "batch_seq").distinct().count() == want
    assert P.check_plan(plan, stats, 32).count() == 0


@pytest.mark.parametrize("codec", ["framed", "msgpack", "arrow"])
def test_payload_round_trip(spark, codec):
    values = [b"", b"x", b"y" * 255, b"z" * 256, b"w" * 65536, "ü漢".encode()] * 3
    df = spark.createDataFrame([("s", i, bytearray(v)) for i, v in enumerate(values)], "shard_id string, ordinal long, body binary")
    packed = K.to_arrow(K.pack(df, 16)) if codec == "arrow" else K.pack(df, 16, codec)
    back = K.unpack(packed, 16, codec).orderBy("ordinal").collect()
    assert [bytes(r.body) for r in back] == values


def test_push_is_flat_and_pull_grows(spark):
    cells = {(r.loader, r.regime): r.modelled_us for r in QUERIES["w02_small"](spark, DATA).collect()}
    push = [cells["push_batch", r] for r in ("lan", "lan_10", "wan")]
    for loader in ("pull_pipeline", "pull_sample"):
        pull = [cells[loader, r] for r in ("lan", "lan_10", "wan")]
        assert pull == sorted(pull) and pull[2] > push[2]
    assert push[2] - push[0] < 2 * 2 * 45_000


def test_concurrency_decides_for_large_records(spark):
    """One stream loses to the pull pipeline at short round trips, two win at all; two are faster than one."""
    one, two = ({(r.loader, r.regime): r.modelled_us for r in QUERIES[n](spark, DATA).collect()} for n in ("w04_synthetic", "w05_synthetic_streams"))
    for regime in ("lan", "lan_1"):
        assert one["push_batch", regime] >= one["pull_pipeline", regime]
    for regime in ("lan", "lan_1", "lan_10", "wan"):
        assert two["push_batch", regime] < one["push_batch", regime] and two["push_batch", regime] < two["pull_pipeline", regime]
        assert one["pull_pipeline", regime] == two["pull_pipeline", regime]
    assert one["push_batch", "wan"] < one["pull_pipeline", "wan"]


def test_more_streams_are_not_slower_than_one(spark):
    t = {}
    for r in QUERIES["streams_sweep"](spark, DATA).collect():
        t.setdefault((r.regime, r.epoch), {})[r.streams] = r.modelled_us
    alone = {(r.regime, r.epoch): r.modelled_us for r in QUERIES["ablate_one_stream"](spark, DATA).collect()}
    assert all(x[2] <= x[1] == alone[k] for k, x in t.items()) and any(x[2] < x[1] for x in t.values())


def test_high_water_marks_bind_at_long_round_trips(spark):
    t = {}
    for r in QUERIES["hwm_bounded"](spark, DATA).collect():
        t.setdefault((r.regime, r.epoch, r.node_id), {})[r.hwm] = r.done
    assert all(x[1] >= x[4] >= x[16] for x in t.values())
    assert all(x[1] > x[16] for k, x in t.items() if k[0] == "wan")
    bound = {(r.regime): r.window_bytes_s for r in QUERIES["hwm_rate_bound"](spark, DATA).collect()}
    assert bound["wan"] < bound["lan_10"]


def test_bounded_push_by_hand(spark):
    """Three batches of one stream, packed at once, 2 us to send, round trip 4: a mark of 1 waits for the word that each was taken."""
    b = spark.createDataFrame([("r", 4, 1, 0, 0, i, 1, 0, 2) for i in range(3)], "regime string, rtt_us long, epoch int, node_id int, worker int, batch_seq int, n long, pack_done long, send_us long")
    ends = lambda hwm, depth: [r.done for r in T.bounded_times(b, 10, hwm, depth).orderBy("batch_seq").collect()]
    assert ends(9, 1) == [18, 28, 38]  # arrivals 8, 10, 12; 10 us each
    assert ends(1, 1) == [18, 28, 38]  # taken 8, 18, 28: the sender is far ahead of the consumer
    slow = lambda hwm, depth: [r.done for r in T.bounded_times(b, 1, hwm, depth).orderBy("batch_seq").collect()]
    assert slow(9, 1) == [9, 11, 13]
    assert slow(1, 1) == [9, 15, 21]  # sends start at 0, 6, 12: taken 8 and 14, known 2 later, minus the 4 of the connection
    t = spark.createDataFrame([("r", 0, 1, 0, 0, i, 1, 0, 1) for i in range(4)], b.schema)
    assert [r.arrival for r in T.bounded_times(t, 10, 1, 3).orderBy("batch_seq").collect()] == [1, 2, 3, 4]  # three are taken ahead, the fourth waits
    assert [r.arrival for r in T.bounded_times(t, 10, 1, 1).orderBy("batch_seq").collect()] == [1, 2, 12, 22]


def test_counters_that_wrap(spark):
    c = spark.createDataFrame([(0, "cpu", 0, t, v) for t, v in enumerate([5, 9, 2, 2, 1])], "node_id int, component string, device int, ts long, counter long")
    assert [r.delta for r in E.counter_deltas(c, 10).orderBy("ts").collect()] == [None, 4, 3, 0, 9]


def test_energy_shares_and_cuts(spark):
    share = {r.regime: r for r in QUERIES["io_share"](spark, DATA).collect()}
    assert share["local"].fetch_share < share["lan_10"].fetch_share < share["wan"].fetch_share
    assert share["local"].fetch_energy_share < share["lan_10"].fetch_energy_share < share["wan"].fetch_energy_share
    cut = {r.regime: r for r in QUERIES["w07_energy_cut"](spark, DATA).collect()}
    assert cut["lan_10"].slower < cut["wan"].slower and 0 < cut["lan_10"].cpu_cut < cut["wan"].cpu_cut


@pytest.mark.parametrize("width", [1, 5, 1 << 14])
def test_cells_do_not_change_results(spark, width):
    """Windows cut at any width: grid, fills, running sums and quantile cells against plain loops."""
    rng = random.Random(3)
    rows = [(node, k, *(rng.randint(0, 99) if rng.random() < 0.4 else None for _ in range(3))) for node in (0, 1) for k in sorted(rng.sample(range(-20, 60), 40))]
    wide = spark.createDataFrame([r for r in rows if any(v is not None for v in r[2:])], "node_id int, slot long, cpu_uj long, dram_uj long, gpu_uj long")
    full = E.on_grid(wide, width)
    for method in ("linear", "previous", "nearest"):
        got = {(r.node_id, r.slot): r for r in E.fill(full, method, cell_slots=width).collect()}
        known = {(r.node_id, r.slot): r.dram_uj for r in full.collect()}
        assert set(got) == set(known) and len(got) == 2 * len({s for _, s in known})
        for (node, k), v in known.items():
            mine = sorted(s for (n, s), x in known.items() if n == node and x is not None)
            p, q = max((s for s in mine if s <= k), default=None), min((s for s in mine if s >= k), default=None)
            a, b = known.get((node, p)), known.get((node, q))
            want = a if q is None else b if p is None else a if p == q else {"linear": int((a * (q - p) + (b - a) * (k - p)) / (q - p)), "previous": a, "nearest": a if k - p <= q - k else b}[method]
            assert got[node, k].dram_uj == want and got[node, k].dram_uj_filled == (v is None and want is not None)
    run = {(r.node_id, r.slot): r.before for r in running_sums(full, ["node_id"], ["slot"], cell_of("slot", width), {"before": F.col("cpu_uj")}).collect()}
    for (node, k), x in run.items():
        assert x == sum(r.cpu_uj or 0 for r in full.collect() if r.node_id == node and r.slot < k)
    index = spark.createDataFrame([("s", i * i, i % 7, 0) for i in range(50)] + [("t", 3, 5, 1)], "shard_id string, record_id long, size long, label int")
    placed = H.shard_index(index, cells=min(width, 64)).where("shard_id = 's'").orderBy("ordinal").collect()
    assert [r.record_id for r in placed] == [i * i for i in range(50)] and [r.offset for r in placed] == [sum(j % 7 + 16 for j in range(i)) for i in range(50)]


def test_plan_check_sees_a_node_without_a_shard(spark):
    stats = spark.createDataFrame([("a", 40), ("b", 10)], "shard_id string, n long")
    plan = P.batch_plan(P.assign_workers(P.assign_nodes(P.shuffle_shards(stats, 1), 2, "replicate"), 1), 32, "node")
    assert P.check_plan(plan, stats, 32, "replicate").count() == 0
    assert [(r.kind, r.shard_id) for r in P.check_plan(plan.where("NOT (node_id = 1 AND shard_id = 'b')"), stats, 32, "replicate").collect()] == [("coverage", "b")]


def test_shard_files_damage_and_large_shards(spark, tmp_path):
    rows = [("s" if i % 3 else "t", i, None if i % 5 else i, bytearray(bytes([i % 256]) * i)) for i in range(300)]
    df = spark.createDataFrame(rows, "shard_id string, record_id long, label int, body binary")
    index = framed.write_shards(df, f"file://{tmp_path}/shards", 3, file_bytes=4000)
    assert index.count() == 300 and index.select("file").distinct().count() > 6
    placed = index.join(H.shard_index(index.select("shard_id", "record_id", "size", "label")).select("shard_id", "record_id", "ordinal"), ["shard_id", "record_id"])
    stats = spark.createDataFrame([("s", 200), ("t", 100)], "shard_id string, n long")
    plan = P.batch_plan(P.assign_workers(P.assign_nodes(P.shuffle_shards(stats, 1), 2), 2), 16, "worker")
    got = framed.read_blocks(framed.blocks_of(plan, placed, 16), f"file://{tmp_path}/shards").collect()
    back = {(r.shard_id, r.ordinal): (r.label, bytes(r.body)) for r in got}
    for name in "st":
        mine = [r for r in rows if r[0] == name]
        assert [back[name, k] for k in range(len(mine))] == [(-1 if r[2] is None else r[2], bytes(r[3])) for r in mine]
    data = struct.pack(framed.HEADER, 3, 0, 1) + b"abc"
    with pytest.raises(ValueError):
        framed.parse_block(data)
    assert framed.write_shards(df.limit(0), f"file://{tmp_path}/none", 2).count() == 0


def test_micro_batches_are_written_once(spark, tmp_path):
    save = sinks.save_batch(f"{tmp_path}/out")
    for _ in (1, 2):
        save(spark.range(5), 0)
    save(spark.range(3), 1)
    assert sinks.saved(spark, f"{tmp_path}/out", "id long").count() == 8 and sinks.saved(spark, f"{tmp_path}/out", "id long", last_only=True).count() == 3
    assert sinks.saved(spark, f"{tmp_path}/nothing", "id long").count() == 0


def test_facade_and_command_line(spark, tmp_path, capsys):
    from batchfeed.__main__ import main
    from batchfeed.api import Engine

    e = Engine(spark, DATA)
    assert rows(e.compare(rtts=("local", "lan", "lan_10", "wan")).toPandas()) == rows(QUERIES["w02_small"](spark, DATA).toPandas())
    assert e.sql("SELECT count(*) AS n FROM feed_tuples").first().n == e.energy().count()
    assert main(["run", "shard_stats", "--data", DATA, "--out", str(tmp_path)]) == 0 and spark.read.parquet(f"{tmp_path}/shard_stats").count() == 20
    assert main(["list"]) == 0 and "w02_small *" in capsys.readouterr().out


def test_training_of_several_epochs(spark):
    rng = np.random.default_rng(3)
    x, y = rng.normal(size=(40, 64)), rng.integers(0, 10, 40)
    df = spark.createDataFrame([(i % 2, [float(v) for v in a], int(b)) for i, (a, b) in enumerate(zip(x, y))], "step long, embedding array<double>, label int")
    losses, _ = R.train(df, 2, epochs=5)
    assert len(losses) == 10 and losses[-1] < losses[0]


def test_conservation(spark):
    t = QUERIES["interpolate_linear"](spark, DATA).persist()
    a = t.groupBy().sum("cpu_uj", "dram_uj", "gpu_uj").first()
    b = E.cluster_series(t).groupBy().sum("cpu_uj", "dram_uj", "gpu_uj").first()
    assert tuple(a) == tuple(b)


def test_data_parallel_equals_one_node(spark):
    rng = np.random.default_rng(1)
    x, y = rng.normal(size=(60, 64)), rng.integers(0, 10, 60)
    step = np.arange(60) // 20
    df = spark.createDataFrame([(int(s), [float(v) for v in a], int(b)) for s, a, b in zip(step, x, y)], "step long, embedding array<double>, label int").repartition(3)
    losses, weights = R.train(df, 3)
    want, other = R.train_reference(x, y, step)
    assert np.allclose(losses, want) and np.allclose(weights, other)


@pytest.mark.parametrize("wide", [0, 4096])
def test_training_needs_no_job_for_each_small_step(spark, wide):
    """Wide steps a job each, small ones in turn: the same losses over epochs, and the latter in far fewer jobs than steps."""
    rng = np.random.default_rng(2)
    x, y, step = rng.normal(size=(400, 64)), rng.integers(0, 10, 400), rng.integers(0, 40, 400)
    df = spark.createDataFrame([(int(s), [float(v) for v in a], int(b)) for s, a, b in zip(step, x, y)], "step long, embedding array<double>, label int")
    spark.sparkContext.setJobGroup(f"train {wide}", "")
    try:
        losses, weights = R.train(df, 40, epochs=2, wide=wide)
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    jobs = len(spark.sparkContext.statusTracker().getJobIdsForGroup(f"train {wide}"))
    steps = np.concatenate([step, step + 40])
    want, other = R.train_reference(np.concatenate([x, x]), np.concatenate([y, y]), steps)
    assert np.allclose(losses, want) and np.allclose(weights, other) and (jobs >= 80 if wide == 0 else jobs < 20)


def test_lookahead_without_end_is_the_closed_form(spark):
    b = spark.createDataFrame([("r", 0, 1, 0, i + 1, n, f) for i, (n, f) in enumerate([(3, 7), (1, 2), (4, 9), (2, 1)])], "regime string, rtt_us long, epoch int, node_id int, turn long, n long, fetch_us long")
    free = L.lookahead(b, "fetch_us", 2, 1 << 30).orderBy("turn").collect()
    closed = T.queue_done(T.queue_done(b, L.NODE, ["turn"], b.fetch_us, "ready"), L.NODE, ["turn"], b.n * 2, "done", T.F.col("ready")).orderBy("turn").collect()
    assert [r.done for r in free] == [r.done for r in closed]
    tight = L.lookahead(b, "fetch_us", 2, 1).orderBy("turn").collect()
    assert all(a.done >= c.done for a, c in zip(tight, free))


@pytest.mark.parametrize("name", ["w13_audit", "w13_audit_energy", "w13_headlines"])
def test_audits_read_a_given_table(spark, tables, name):
    """The printed figures stand beside those modelled from documents."""
    df = QUERIES[name](spark, DATA)
    assert any(f.endswith("documents.parquet") for f in df.inputFiles())
    got, want = df.toPandas(), tables.execute(ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns) and rows(got) == rows(want) and len(got) == {"w13_audit": 24, "w13_audit_energy": 6, "w13_headlines": 4}[name]
    assert any("modelled" in c for c in got.columns) and not got.filter(like="modelled").isna().any(axis=None)


@pytest.mark.parametrize("within,us", [("1 hour", 3_600_000_000), ("3 microseconds", 3)])
def test_sends_meet_receipts_of_their_time_only(spark, within, us):
    """Time is part of the join's key; pairs on and beside every edge, before 1970 too, are found once."""
    rng = random.Random(5)
    rows = [(i, rng.choice((-1, 0, 1)) * us // 4 * rng.randint(0, 9) + rng.randint(-1, 1), rng.randint(0, 7), rng.choice(("view", "click", "error"))) for i in range(400)] + [(400, None, 1, "view"), (401, None, 1, "click")]
    e = spark.createDataFrame(rows, "event_id long, us long, user_id long, event_type string").withColumn("ts", F.timestamp_micros("us")).drop("us")
    joined = monitor.send_receipt(e, within)
    want = sorted((a[2] % 4, a[0], b[0]) for a in rows for b in rows if a[3] == "view" and b[3] == "click" and a[2] % 4 == b[2] % 4 and None not in (a[1], b[1]) and a[1] <= b[1] < a[1] + us)
    assert sorted(tuple(r) for r in joined.collect()) == want and len(want) > 100
    keys = [line for line in joined._jdf.queryExecution().executedPlan().toString().split("\n") if "Join" in line]
    assert keys and all("[node_id" in line and ", quarter" in line for line in keys)


def test_streams_read_folders_and_overlapping_files(spark, tmp_path):
    e = spark.read.parquet(f"{DATA}/events.parquet")
    names = ("stream_tick_energy", "stream_dedup")
    want = {n: rows(QUERIES[n](spark, DATA).toPandas()) for n in names}
    e.repartition(3).write.parquet(f"{tmp_path}/folder/events.parquet")
    os.makedirs(f"{tmp_path}/files")
    for i, part in enumerate(sorted(glob.glob(f"{tmp_path}/folder/events.parquet/*.parquet"))):
        os.link(part, f"{tmp_path}/files/events.parquet.{i}")
    for layout in ("folder", "files"):
        for n in names:
            got = rows(QUERIES[n](spark, f"{tmp_path}/{layout}").toPandas())
            assert got and got == want[n]


@pytest.fixture(scope="module")
def answers(spark):
    """Results of the queries, several at a time."""
    with ThreadPoolExecutor(6) as pool:
        yield {n: pool.submit(lambda n=n: QUERIES[n](spark, DATA).toPandas()) for n in sorted(ORACLES)}
        pool.shutdown(cancel_futures=True)


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_oracle(answers, tables, name):
    got, want = answers[name].result(), tables.execute(ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns) and rows(got) == rows(want)
