"""Queries that write and read: shard files, their index, payload streams, sinks, and the SQL surface."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from ..config import DAY_US, HOUR_US
from ..functions.columns import div, micros
from ..functions.joins import with_small
from ..operators import energy as E, payload as K, shards as H
from ..sources import framed
from ..sources.storage import new_path, written
from ..sources.tables import nodes, read, records, samples
from ..sql import register_views
from ..streaming import monitor as M, sinks
from . import energy_queries as EQ, feed_queries as Q
from .registry import ORACLES, query

PARTS = 4


def labelled_bodies(spark, d) -> DataFrame:
    """Documents as shard_id, record_id, label, body."""
    labels = read(spark, d, "labels").select("doc_id", "quality")
    docs = read(spark, d, "documents").select("doc_id", "source", "text").join(labels, "doc_id", "left")
    return docs.select(F.col("source").alias("shard_id"), F.col("doc_id").alias("record_id"), F.col("quality").alias("label"), F.encode("text", "UTF-8").alias("body"))


def stored_shards(spark, d) -> tuple[str, DataFrame]:
    """Shard files of the documents, and their index read back from its JSON lines."""
    folder, found = framed.build_shards(labelled_bodies(spark, d), PARTS)
    placed = H.shard_index(found.select("shard_id", "record_id", "size", "label")).select("shard_id", "record_id", "ordinal", "offset")
    path = new_path(spark, "index")
    H.write_index_json(found.join(placed, ["shard_id", "record_id"]).drop("record_id"), path)
    return folder, H.read_index_json(spark, path, "file:string,position:long,size:long,label:int,offset:long")


# --- shard files ------------------------------------------------------------------
@query("index_json_roundtrip", f'with {Q.base_sql()} select shard_id, ordinal, "offset", size, label from ix')
def index_json_roundtrip(spark, d):
    """The index written as JSON lines and read back."""
    path = new_path(spark, "index")
    H.write_index_json(H.shard_index(records(spark, d, "documents")).drop("record_id"), path)
    return H.read_index_json(spark, path).select("shard_id", "ordinal", "offset", "size", "label")


_STORED = """with b as (select source shard_id, row_number() over (partition by source order by doc_id) - 1 ordinal, coalesce(quality, -1)::int as label, md5(text) digest
 from documents left join labels using (doc_id))"""


@query("shards_roundtrip", f"{_STORED} select e.epoch::bigint epoch, shard_id, ordinal, label, digest from b, (values (1), (2)) e(epoch)")
def shards_roundtrip(spark, d):
    """Every epoch's batches read from shard files in contiguous blocks."""
    folder, index = stored_shards(spark, d)
    blocks = framed.blocks_of(Q.plan(spark, d, scope="worker"), written(index, "index"), Q.B)
    return framed.read_blocks(blocks, folder).select("epoch", "shard_id", "ordinal", "label", F.md5("body").alias("digest"))


@query("block_reads", f"""with {Q.plan_sql(scope='worker')} select epoch::bigint epoch, sum(pl.n)::bigint records, sum(size)::bigint bytes
 from pl join (select pl.epoch e2, pl.shard_id s2, first_ordinal f2, sum(size + 16) size from pl
 join ix on pl.shard_id = ix.shard_id and ordinal >= first_ordinal and ordinal < first_ordinal + pl.n
 group by all) on epoch = e2 and shard_id = s2 and first_ordinal = f2 group by all""")
def block_reads(spark, d):
    """Records and bytes of the blocks that a plan reads."""
    _, index = stored_shards(spark, d)
    blocks = framed.blocks_of(Q.plan(spark, d, scope="worker"), index, Q.B)
    return blocks.groupBy(F.col("epoch").cast("long").alias("epoch")).agg(F.sum("n_block").alias("records"), F.sum(F.col("block_end") - F.col("block_start")).alias("bytes"))


# --- payloads ---------------------------------------------------------------------
@query("pack_arrow_roundtrip", ORACLES["unpack_roundtrip"])
def pack_arrow_roundtrip(spark, d):
    """Payloads as Arrow streams, and back."""
    return K.unpack(K.to_arrow(K.pack(Q.bodies(spark, d), Q.B)), Q.B, "arrow").select("shard_id", "ordinal", F.md5("body").alias("digest"))


@query("udtf_unpack", ORACLES["unpack_roundtrip"])
def udtf_unpack(spark, d):
    """Payloads taken apart by a table function in SQL."""
    K.register_unpack(spark)
    K.pack(Q.bodies(spark, d), Q.B, "msgpack").createOrReplaceTempView("feed_payloads")
    return spark.sql(f"SELECT p.shard_id, p.batch_seq * {Q.B} + r.place AS ordinal, md5(r.body) AS digest FROM feed_payloads p, LATERAL unpack_records(p.body, 'msgpack') r")


@query("receive_stream", ORACLES["unpack_roundtrip"])
def receive_stream(spark, d):
    """Payload files taken in as a stream, a few a trigger, unpacked into a table that each micro-batch adds to once."""
    path = new_path(spark, "payloads")
    K.pack(Q.bodies(spark, d), Q.B, "msgpack").repartition(6).write.parquet(f"{path}/in")
    queue = spark.readStream.schema("shard_id string, batch_seq long, n_records long, body binary").option("maxFilesPerTrigger", 2).parquet(f"{path}/in")
    got = K.unpack(queue, Q.B, "msgpack").select("shard_id", "ordinal", F.md5("body").alias("digest"))
    for _ in (1, 2):  # the second run finds nothing new
        sinks.drain(got, f"{path}/out", f"{path}/checkpoint")
    return sinks.saved(spark, f"{path}/out", got.schema)


# --- sinks ------------------------------------------------------------------------
@query("sink_partitioned_energy", f"with {EQ.S} select node_id, component, epoch_us(ts) // 86400000000 as day, count(*) n, sum(power_cw)::bigint total_cw from samples group by all")
def sink_partitioned_energy(spark, d):
    """Tick sums of a stream in a table by node and day, read back by day; retried micro-batches overwrite themselves."""
    path = new_path(spark, "energy")
    ticks = M.samples_of(M.event_stream(spark, d)).select("node_id", "component", div(micros(F.col("ts")), DAY_US).alias("day"), div(micros(F.col("ts")), HOUR_US).alias("slot"), "power_cw")
    schema = "node_id int, component string, day long, slot long, power_cw long"
    for _ in (1, 2):
        sinks.drain(ticks, f"{path}/out", f"{path}/checkpoint", partition_by=("node_id", "day"))
    return sinks.saved(spark, f"{path}/out", schema).groupBy("node_id", "component", "day").agg(F.count("*").alias("n"), F.sum("power_cw").alias("total_cw"))


_SUMS = "count(*) n, sum(cpu_uj)::bigint cpu_uj, sum(dram_uj)::bigint dram_uj, sum(gpu_uj)::bigint gpu_uj"


@query("sink_local_and_central", f"with {EQ.T} select s.store, node_id, {_SUMS} from t, (values ('local'), ('central')) s(store) group by all")
def sink_local_and_central(spark, d):
    """The same energies from a store a node and from one table."""
    rows, path = EQ.tuples(spark, d), new_path(spark, "stores")
    rows = written(rows, "tuples")
    E.local_stores(rows, f"{path}/local")
    E.central_store(rows, f"{path}/central")
    sums = [F.count("*").alias("n"), *(F.sum(c).alias(c) for c in E.PARTS)]
    total = lambda name: spark.read.schema(rows.schema).parquet(f"{path}/{name}").groupBy(F.lit(name).alias("store"), "node_id").agg(*sums)
    return total("local").unionByName(total("central"))


# --- scans, joins, aggregates -----------------------------------------------------
@query("filter_time_component", f"""with {EQ.S} select node_id, component, count(*) n, max(power_cw) peak_cw from samples where ts >= timestamp '2024-01-05' and ts < timestamp '2024-01-12' and component in ('cpu', 'dram')
 group by all""")
def filter_time_component(spark, d):
    """Filters on time and component, both of which reach the scan, the latter as event types."""
    s = samples(spark, d, "cpu", "dram").where("ts >= TIMESTAMP_NTZ '2024-01-05' AND ts < TIMESTAMP_NTZ '2024-01-12'")
    return s.groupBy("node_id", "component").agg(F.count("*").alias("n"), F.max("power_cw").alias("peak_cw"))


@query("join_broadcast_nodes", f"""with {EQ.S} select site, role, component, count(*) n, sum(power_cw)::bigint total_cw from samples
 join (values (0, 'compute', 'site-1'), (1, 'compute', 'site-1'), (2, 'compute', 'site-2'), (3, 'storage', 'site-1')) n(node_id, role, site) using (node_id)
 group by all""")
def join_broadcast_nodes(spark, d):
    """Samples with their nodes; the node table is broadcast as long as it is counted to be small."""
    j = with_small(samples(spark, d), nodes(spark), "node_id")
    return j.groupBy("site", "role", "component").agg(F.count("*").alias("n"), F.sum("power_cw").alias("total_cw"))


@query("udaf_trapezoid", f"""with {EQ.S}, p as (select *, lag(ts) over w t0, lag(power_cw) over w p0 from samples window w as (partition by node_id, component, device, epoch_us(ts) // 86400000000
 order by ts)) select node_id, component, device, epoch_us(ts) // 86400000000 as day, coalesce(sum((epoch_us(ts) - epoch_us(t0)) * (power_cw + p0)), 0)::bigint twice_cw_us
 from p group by all""")
def udaf_trapezoid(spark, d):
    """The integral of each channel's power over a day by an aggregate of its own; a group is one channel's day."""
    s = samples(spark, d).withColumn("t_us", micros(F.col("ts"))).withColumn("day", div(F.col("t_us"), DAY_US))
    return s.groupBy("node_id", "component", "device", "day").agg(E.trapezoid()("t_us", "power_cw").alias("twice_cw_us"))


@query("sql_interval_energy", ORACLES["interval_energy_whole"])
def sql_interval_energy(spark, d):
    """The interval query as text over the registered views."""
    register_views(spark, d)
    return spark.sql(f"""
        SELECT r.run_id, r.node_id, count(t.slot) AS n_slots, sum(t.cpu_uj) AS cpu_uj, sum(t.dram_uj) AS dram_uj, sum(t.gpu_uj) AS gpu_uj
        FROM (SELECT *, explode(sequence(start_us DIV {DAY_US}, end_us DIV {DAY_US})) AS day FROM feed_runs) r
        LEFT JOIN (SELECT *, slot * {HOUR_US} DIV {DAY_US} AS day FROM feed_tuples) t
          ON r.node_id = t.node_id AND r.day = t.day AND t.slot * {HOUR_US} >= r.start_us AND t.slot * {HOUR_US} < r.end_us
        GROUP BY r.run_id, r.node_id""")
