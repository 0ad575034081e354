"""Queries of the shard store, planner, payloads, transport, loaders and measures."""

from __future__ import annotations

from dataclasses import asdict

from pyspark.sql import DataFrame, Window as W, functions as F

from ..config import FEED, MODEL_A, MODEL_B, REGIMES, Feed
from ..functions.columns import div, ratio
from ..operators import loaders as L, payload as K, planner as P, shards as H, transport as T
from ..sources.tables import read, records, regimes
from .registry import query

E, N, TW, B = FEED.epochs, FEED.nodes, FEED.workers, FEED.batch
PAGES = L.scaled(FEED, size_scale=60)
SETS = ("documents", "pages", "embeddings", "lineitem", "conversations")


def records_sql(name: str) -> str:
    """DuckDB form of sources.tables.records."""
    return {
        "documents": "select source shard_id, d.doc_id record_id, strlen(text)::bigint size, coalesce(quality, -1)::int label from documents d left join labels using (doc_id)",
        "pages": "select (page_id % 8)::varchar shard_id, page_id record_id, strlen(html)::bigint size, -1 label from pages",
        "embeddings": "select (vec_id % 8)::varchar shard_id, vec_id record_id, 256::bigint size, label from embeddings",
        "conversations": "select (conv_id % 4)::varchar shard_id, conv_id record_id, sum(strlen(text))::bigint size, -1 label from conversations group by conv_id",
        "lineitem": """select l_suppkey::varchar shard_id, row_number() over () record_id, 64 + max(l_quantity)::bigint size, -1 label
 from lineitem group by l_suppkey, l_orderkey, l_linenumber, l_partkey, l_shipdate""",
    }[name]


def base_sql(name: str = "documents") -> str:
    return f"""r as ({records_sql(name)}), st as (select shard_id, count(*) n, sum(size + 16)::bigint bytes from r group by all),
ix as (select shard_id, record_id, row_number() over w - 1 ordinal, coalesce(sum(size + 16) over (partition by shard_id order by record_id rows between unbounded preceding and 1 preceding), 0)::bigint "offset", size, label from r window w as (partition by shard_id order by record_id))"""


def assign_sql(name: str = "documents", nodes: int = N, epochs: int = E, split: str = "striped", coverage: str = "partition", workers: int = TW) -> str:
    t = workers
    deal = f"k % {nodes} node_id, k // {nodes} pos from od" if coverage == "partition" else f"g node_id, k pos from od, range(0, {nodes}) t(g)"
    worker = {
        "striped": f"""select *, pos % {t} worker, 0 "first", n "count" from ag""",
        "chunked": f"""select *, ntile({t}) over (partition by epoch, node_id order by pos) - 1 worker, 0 "first", n "count" from ag""",
        "intra_shard": f"""select *, g worker, g * (n // {t}) + least(g, n % {t}) "first", n // {t} + (g < n % {t})::int "count"
  from ag, range(0, {t}) t(g) where n // {t} + (g < n % {t})::int > 0""",
    }[split]
    return base_sql(name) + f""", od as (select epoch, shard_id, n, row_number() over (partition by epoch order by md5('42:' || epoch || ':' || shard_id), shard_id) - 1 k from st, range(1, {epochs + 1}) e(epoch)),
ag as (select epoch, shard_id, n, k, {deal}), wk as ({worker})"""


def plan_sql(name: str = "documents", scope: str = "shard", workers: int = TW, **how) -> str:
    """The plan as `pl`; wider scopes number each record and cut the numbering, not the shards."""
    head = assign_sql(name, workers=workers, **how)
    if scope == "shard":
        return head + f""", pl as (select epoch, node_id, worker, row_number() over (partition by epoch, node_id, worker order by pos, "first", j) - 1 batch_seq, shard_id, "first" + j * {B} first_ordinal, least({B}, "count" - j * {B}) n from (select *, unnest(range(0, ("count" + {B - 1}) // {B})) j from wk))"""
    keys = "epoch, node_id, worker" if scope == "worker" else "epoch, node_id"
    worker = "worker" if scope == "worker" else f"b % {workers}"
    return head + f""", rec as (select epoch, node_id, worker, shard_id, "first" + i o, (row_number() over (partition by {keys} order by pos, "first", i) - 1) // {B} b from (select *, unnest(range(0, "count")) i from wk)),
pl as (select epoch, node_id, {worker} worker, b batch_seq, shard_id, min(o) first_ordinal, count(*) n from rec group by all)"""


def batches_sql(name: str = "documents", **how) -> str:
    return plan_sql(name, **how) + ', bt as (select epoch, node_id, worker, batch_seq, count(*) n, sum(size + 16)::bigint bytes, count(distinct pl.shard_id) n_ranges from pl join ix on pl.shard_id = ix.shard_id and ordinal >= first_ordinal and ordinal < first_ordinal + pl.n group by all)'


def stats(spark, d, name: str = "documents") -> DataFrame:
    return H.shard_stats(records(spark, d, name))


def work(spark, d, name: str = "documents", nodes: int = N, epochs: int = E, split: str = "striped", coverage: str = "partition", workers: int = TW) -> DataFrame:
    return P.assign_workers(P.assign_nodes(P.shuffle_shards(stats(spark, d, name), epochs), nodes, coverage), workers, split)


def plan(spark, d, name: str = "documents", scope: str = "shard", tail: str = "keep", workers: int = TW, **how) -> DataFrame:
    return P.batch_plan(work(spark, d, name, workers=workers, **how), B, scope, tail, workers)


def batches(spark, d, name: str = "documents", **how) -> DataFrame:
    return P.batches(P.with_bytes(plan(spark, d, name, **how), H.shard_index(records(spark, d, name))))


# --- shards -----------------------------------------------------------------------
for _set in SETS[:3]:
    query(f"shard_index_{_set}", f'with {base_sql(_set)} select shard_id, record_id, ordinal, "offset", size, label from ix')(lambda spark, d, s=_set: H.shard_index(records(spark, d, s)))


@query("shard_index_lineitem", f'with {base_sql("lineitem")} select shard_id, count(*) n, max("offset" + size + 16)::bigint bytes from ix group by all')
def shard_index_lineitem(spark, d):
    return H.shard_index(records(spark, d, "lineitem")).groupBy("shard_id").agg(F.count("*").alias("n"), F.max(F.col("offset") + F.col("size") + 16).alias("bytes"))


query("conversation_samples", f'with {base_sql("conversations")} select shard_id, record_id, ordinal, "offset", size, label from ix')(lambda spark, d: H.shard_index(records(spark, d, "conversations")))


@query("shard_stats", f"""with {base_sql()} select shard_id, n, bytes, largest, floor(total::double / n::double * 1e6 + 0.5) / 1e6 mean_size
 from st join (select shard_id, max(size) largest, sum(size) total from r group by all) using (shard_id)""")
def shard_stats(spark, d):
    return stats(spark, d)


@query("label_histogram", f"with {base_sql()} select shard_id, label, count(*) n from r group by all")
def label_histogram(spark, d):
    return H.label_histogram(records(spark, d, "documents"))


@query("conversion_amortized", f"with {base_sql()} select jobs, c convert_us, c // jobs us_per_job from (select sum(bytes)::bigint c from st), range(1, 11) t(jobs)")
def conversion_amortized(spark, d):
    return H.amortized_cost(stats(spark, d), 10).select(F.col("jobs").cast("long").alias("jobs"), "convert_us", "us_per_job")


@query("project_sizes", """select source, count(*) n, sum(strlen(text))::bigint bytes, sum(length(text))::bigint chars
 from documents where lang in ('en', 'de') and n_chars between 100 and 5000 group by all""")
def project_sizes(spark, d):
    docs = read(spark, d, "documents").where("lang IN ('en', 'de') AND n_chars BETWEEN 100 AND 5000")
    return docs.groupBy("source").agg(F.count("*").alias("n"), F.sum(F.octet_length("text").cast("long")).alias("bytes"), F.sum(F.length("text").cast("long")).alias("chars"))


# --- planner ----------------------------------------------------------------------
@query("epoch_shuffle", f"with {assign_sql()} select epoch, shard_id, n, k from od")
def epoch_shuffle(spark, d):
    return P.shuffle_shards(stats(spark, d), E)


@query("assign_round_robin", f"with {assign_sql()} select epoch, shard_id, node_id, pos from ag")
def assign_round_robin(spark, d):
    return P.assign_nodes(P.shuffle_shards(stats(spark, d), E), N).select("epoch", "shard_id", "node_id", "pos")


for _split in ("striped", "chunked", "intra_shard"):
    query(f"workers_{_split}", f'with {assign_sql(split=_split)} select epoch, node_id, worker, shard_id, "first", "count" from wk')(lambda spark, d, s=_split: work(spark, d, split=s).select("epoch", "node_id", "worker", "shard_id", "first", "count"))

_PLAN = "select epoch, node_id, worker, batch_seq, shard_id, first_ordinal, n from pl"
for _name, _how in {
    "batch_plan_shard": {}, "batch_plan_worker": {"scope": "worker"}, "batch_plan_node": {"scope": "node"}, "plan_replicate": {"coverage": "replicate", "scope": "node"},
    "batch_plan_intra_shard": {"split": "intra_shard"}, "batch_plan_pages": {"name": "pages"}, "batch_plan_lineitem": {"name": "lineitem", "scope": "worker"},
}.items():
    query(_name, f"with {plan_sql(**_how)} {_PLAN}")(lambda spark, d, h=_how: plan(spark, d, **h))


@query("plan_drop_last", f"with {plan_sql(scope='worker')} {_PLAN} qualify sum(n) over (partition by epoch, node_id, worker, batch_seq) = {B}")
def plan_drop_last(spark, d):
    return plan(spark, d, scope="worker", tail="drop_last")


@query("plan_pad", f"""with {plan_sql(scope='worker')} select epoch, node_id, worker, batch_seq, shard_id, first_ordinal, n, {B} - sum(n) over (partition by epoch, node_id, worker, batch_seq)::bigint padded
 from pl""")
def plan_pad(spark, d):
    return plan(spark, d, scope="worker", tail="pad")


_STEPS = """b as (select *, row_number() over (partition by epoch, node_id order by batch_seq, worker) - 1 step
 from (select epoch, node_id, worker, batch_seq, sum(n)::bigint n from pl group by all)), o as (select *, count(*) over (partition by epoch, node_id) own
 from b)"""


@query("plan_equalize_truncate", f"""with {plan_sql()}, {_STEPS} select epoch, node_id, worker, batch_seq, n, step, false is_repeat
 from (select *, min(own) over (partition by epoch) m from o) where step < m""")
def plan_equalize_truncate(spark, d):
    return P.equalize(plan(spark, d), "truncate")


@query("plan_equalize_repeat", f"""with {plan_sql(nodes=3)}, {_STEPS}, m as (select *, max(own) over (partition by epoch) m from o)
 select m.epoch, m.node_id, worker, batch_seq, n, s step, s >= own is_repeat from m, range(0, 100000) t(s)
 where s < m and s % own = step""")
def plan_equalize_repeat(spark, d):
    return P.equalize(plan(spark, d, nodes=3), "repeat")


@query("plan_check", "select 'ok' kind, 1 epoch, '' shard_id, 0 n where false")
def plan_check(spark, d):
    st = stats(spark, d)
    found = [P.check_plan(plan(spark, d, scope=s), st, B) for s in ("shard", "worker", "node")] + [P.check_plan(plan(spark, d, scope="node", coverage="replicate"), st, B, "replicate")]
    out = found[0]
    for f in found[1:]:
        out = out.unionByName(f)
    return out


@query("batch_counts", f"with {base_sql()} select sum((n + {B - 1}) // {B})::bigint by_shard, ((sum(n) + {B - 1}) // {B})::bigint by_node from st")
def batch_counts(spark, d):
    return P.expected_batches(stats(spark, d), B)


@query("replicate_guarantee", f"""with {plan_sql(coverage='replicate', scope='node')} select epoch, node_id, count(distinct batch_seq) batches, (select (sum(n) + {B - 1}) // {B}
 from st)::bigint expected from pl group by all""")
def replicate_guarantee(spark, d):
    p = plan(spark, d, coverage="replicate", scope="node").groupBy("epoch", "node_id").agg(F.countDistinct("batch_seq").alias("batches"))
    return p.crossJoin(F.broadcast(P.expected_batches(stats(spark, d), B).select(F.col("by_node").alias("expected"))))


_PLACE = "pc as (select shard_id, (row_number() over (order by shard_id) - 1) % 2 server from st)"


@query("placement_locality", f"""with {plan_sql(coverage='replicate')}, {_PLACE} select epoch, node_id, server = node_id is_local, sum(n)::bigint records, count(*) ranges
 from pl join pc using (shard_id) group by all""")
def placement_locality(spark, d):
    return P.locality(plan(spark, d, coverage="replicate"), P.place_shards(stats(spark, d), 2))


@query("placement_balanced", f"""with {base_sql()}, k as (select *, row_number() over (order by bytes desc, shard_id) - 1 k
 from st) select shard_id, case when k % 8 < 4 then k % 8 else 7 - k % 8 end server from k""")
def placement_balanced(spark, d):
    return P.place_shards(stats(spark, d), 4, "balanced").select("shard_id", "server")


@query("load_balance", f"""with {batches_sql()} select *, floor((bytes * {TW})::double / (sum(bytes) over (partition by epoch, node_id))::double * 1e6 + 0.5) / 1e6 skew
 from (select epoch, node_id, worker, count(*) batches, sum(n)::bigint records, sum(bytes)::bigint bytes
 from bt group by all)""")
def load_balance(spark, d):
    by = batches(spark, d).groupBy("epoch", "node_id", "worker").agg(F.count("*").alias("batches"), F.sum("n").alias("records"), F.sum("bytes").alias("bytes"))
    return by.withColumn("skew", ratio(F.col("bytes") * TW, F.sum("bytes").over(W.partitionBy("epoch", "node_id"))))


@query("read_ops", f"with {plan_sql()} select epoch, sum(n)::bigint sample_reads, count(*) range_reads from pl group by all")
def read_ops(spark, d):
    return plan(spark, d).groupBy("epoch").agg(F.sum("n").alias("sample_reads"), F.count("*").alias("range_reads"))


@query("shuffle_displacement", f"""with {assign_sql(epochs=3)} select a.epoch, sum(abs(a.k - b.k))::bigint moved, count(*) filter (a.k = b.k) fixed
 from od a join od b on a.shard_id = b.shard_id and b.epoch = a.epoch + 1 group by all""")
def shuffle_displacement(spark, d):
    od = P.shuffle_shards(stats(spark, d), 3)
    nxt = od.select("shard_id", (F.col("epoch") - 1).alias("epoch"), F.col("k").alias("k2"))
    return od.join(nxt, ["shard_id", "epoch"]).groupBy("epoch").agg(F.sum(F.abs(F.col("k") - F.col("k2"))).alias("moved"), F.count(F.when(F.col("k") == F.col("k2"), 1)).alias("fixed"))


@query("batch_label_entropy", f"""with {batches_sql(epochs=1)}, h as (select epoch, node_id, worker, batch_seq, label, count(*)::double c
 from pl join ix on pl.shard_id = ix.shard_id and ordinal >= first_ordinal and ordinal < first_ordinal + pl.n
 group by all), p as (select *, c / sum(c) over (partition by epoch, node_id, worker, batch_seq) p
 from h) select epoch, node_id, worker, batch_seq, floor(-sum(p * ln(p)) * 1e4 + 0.5) / 1e4 entropy
 from p group by all""")
def batch_label_entropy(spark, d):
    ix = H.shard_index(records(spark, d, "documents")).select("shard_id", F.call_function("div", "ordinal", F.lit(B).cast("long")).alias("cell"), "label")
    p = plan(spark, d, epochs=1).withColumn("cell", div(F.col("first_ordinal"), B))
    h = p.join(ix, ["shard_id", "cell"]).groupBy("epoch", "node_id", "worker", "batch_seq", "label").agg(F.count("*").cast("double").alias("c"))
    q = F.col("c") / F.sum("c").over(W.partitionBy("epoch", "node_id", "worker", "batch_seq"))
    return h.withColumn("p", q).groupBy("epoch", "node_id", "worker", "batch_seq").agg((F.floor(-F.sum(F.col("p") * F.log("p")) * 1e4 + 0.5) / F.lit(1e4)).alias("entropy"))


@query("record_shuffle_buffer", f"""with {base_sql()} select shard_id, ordinal, (ordinal // 16) * 16 + row_number() over (partition by shard_id, ordinal // 16
 order by md5('42:' || shard_id || ':' || ordinal), ordinal) - 1 place from ix""")
def record_shuffle_buffer(spark, d):
    return P.record_shuffle(H.shard_index(records(spark, d, "documents")), 16)


@query("except_plan_epochs", f"with {assign_sql()} select shard_id, node_id from ag where epoch = 1 except select shard_id, node_id from ag where epoch = 2")
def except_plan_epochs(spark, d):
    ag = P.assign_nodes(P.shuffle_shards(stats(spark, d), E), N).select("epoch", "shard_id", "node_id")
    return ag.where("epoch = 1").drop("epoch").subtract(ag.where("epoch = 2").drop("epoch"))


@query("intersect_plan_epochs", f"with {assign_sql()} select shard_id, node_id from ag where epoch = 1 intersect select shard_id, node_id from ag where epoch = 2")
def intersect_plan_epochs(spark, d):
    ag = P.assign_nodes(P.shuffle_shards(stats(spark, d), E), N).select("epoch", "shard_id", "node_id")
    return ag.where("epoch = 1").drop("epoch").intersect(ag.where("epoch = 2").drop("epoch"))


@query("semi_labeled", "select source, count(*) n from documents where doc_id in (select doc_id from labels) group by all")
def semi_labeled(spark, d):
    return read(spark, d, "documents").join(read(spark, d, "labels"), "doc_id", "left_semi").groupBy("source").agg(F.count("*").alias("n"))


@query("anti_plan_missing", "select source, count(*) n from documents where doc_id not in (select doc_id from labels) group by all")
def anti_plan_missing(spark, d):
    return read(spark, d, "documents").join(read(spark, d, "labels"), "doc_id", "left_anti").groupBy("source").agg(F.count("*").alias("n"))


@query("topk_shards", f"with {base_sql()} select shard_id, n, bytes from st order by bytes desc, shard_id limit 5")
def topk_shards(spark, d):
    return stats(spark, d).select("shard_id", "n", "bytes").orderBy(F.desc("bytes"), "shard_id").limit(5)


# --- payload ----------------------------------------------------------------------
def bodies(spark, d) -> DataFrame:
    """Documents as shard_id, ordinal, body."""
    docs = read(spark, d, "documents")
    k = (F.row_number().over(W.partitionBy("source").orderBy("doc_id")) - 1).cast("long")
    return docs.select(F.col("source").alias("shard_id"), k.alias("ordinal"), F.encode("text", "UTF-8").alias("body"))


_BODIES = f"""b as (select source shard_id, row_number() over (partition by source order by doc_id) - 1 o, hex(encode(text)) h, strlen(text) n
 from documents), c as (select *, o // {B} batch_seq from b)"""


@query("pack_framed_digest", f"""with {_BODIES} select shard_id, batch_seq, count(*) n_records, (sum(n) + 4 * count(*))::bigint bytes, md5(unhex(string_agg(printf('%08x', n) || h, ''
 order by o))) digest from c group by all""")
def pack_framed_digest(spark, d):
    return K.pack(bodies(spark, d), B).select("shard_id", "batch_seq", "n_records", F.octet_length("body").cast("long").alias("bytes"), F.md5("body").alias("digest"))


@query("pack_msgpack_digest", f"""with {_BODIES} select shard_id, batch_seq, count(*) n_records, md5(unhex(case when count(*) < 16 then printf('%02x', 144 + count(*)) else 'dc' || printf('%04x', count(*)) end || string_agg(case when n < 256 then 'c4' || printf('%02x', n) when n < 65536 then 'c5' || printf('%04x', n) else 'c6' || printf('%08x', n) end || h, ''
 order by o))) digest from c group by all""")
def pack_msgpack_digest(spark, d):
    return K.pack(bodies(spark, d), B, "msgpack").select("shard_id", "batch_seq", "n_records", F.md5("body").alias("digest"))


@query("unpack_roundtrip", "select source shard_id, row_number() over (partition by source order by doc_id) - 1 ordinal, md5(text) digest from documents")
def unpack_roundtrip(spark, d):
    return K.unpack(K.pack(bodies(spark, d), B, "msgpack"), B, "msgpack").select("shard_id", "ordinal", F.md5("body").alias("digest"))


@query("payload_overhead", f"""with {_BODIES} select shard_id, count(distinct batch_seq) payloads, floor((sum(n) + 4 * count(*))::double / sum(n)::double * 1e6 + 0.5) / 1e6 overhead
 from c group by all""")
def payload_overhead(spark, d):
    p = K.pack(bodies(spark, d), B)
    return p.groupBy("shard_id").agg(F.count("*").alias("payloads"), ratio(F.sum(F.octet_length("body").cast("long")), F.sum(F.octet_length("body").cast("long") - 4 * F.col("n_records"))).alias("overhead"))


# --- transport --------------------------------------------------------------------
def regimes_sql(names: tuple = ()) -> str:
    return "rg as (select * from (values " + ", ".join(f"('{n}', {v}::bigint)" for n, v in REGIMES if not names or n in names) + ") t(regime, rtt_us))"


def service_sql(feed: Feed = FEED) -> str:
    s = asdict(feed)
    return """sv as (select *, n_ranges * {seek_us} + bytes * {size_scale} * {workers} * 1000000 // {disk_bytes_s} read_us, {pack_us} + bytes * {size_scale} * {pack_ns_byte} // 1000 pack_us, bytes * {size_scale} * {workers} * 1000000 // {net_bytes_s} send_us from bt, rg)""".format(**s)


def queue_sql(source: str, target: str, keys: str, order: str, service: str, out: str, ready: str | None) -> str:
    """A stage as a recursive walk from batch to batch: the definition, not the closed form."""
    first = service if ready is None else f"{ready} + {service}"
    step = f"p.{out} + x.{service}" if ready is None else f"greatest(p.{out}, x.{ready}) + x.{service}"
    on = " and ".join(f"x.{k.strip()} = p.{k.strip()}" for k in keys.split(","))
    return f"""{target}_n as (select *, row_number() over (partition by {keys} order by {order}) rn_{target}
 from {source}), {target} as (select *, ({first})::bigint {out} from {target}_n where rn_{target} = 1
 union all select x.*, ({step})::bigint from {target}_n x join {target} p on {on} and x.rn_{target} = p.rn_{target} + 1)"""


ST, ND = "regime, epoch, node_id, worker", "regime, epoch, node_id"


def push_sql(name: str = "documents", feed: Feed = FEED, names: tuple = (), delivery: str = "arrival", pipelined: bool = True, prebatched: bool = True, **how) -> str:
    """CTEs up to `dl`: delivered batches of push_batch."""
    parts = [batches_sql(name, **how), regimes_sql(names), service_sql(feed)]
    source = "sv"
    if not prebatched:
        parts.append(f"sw as (select * replace (send_us + n * (rtt_us + {feed.pack_us}) as send_us) from sv)")
        source = "sw"
    if pipelined:
        parts += [queue_sql(source, "p1", ST, "batch_seq", "read_us", "read_done", None), queue_sql("p1", "p2", ST, "batch_seq", "pack_us", "pack_done", "read_done"), queue_sql("p2", "p3", ST, "batch_seq", "send_us", "send_done", "pack_done")]
    else:
        parts.append("p3 as (select *, (sum(read_us + pack_us + send_us + rtt_us) over (partition by regime, epoch, node_id, worker order by batch_seq))::bigint send_done from " + source + ")")
    parts.append("ar as (select *, send_done + rtt_us + rtt_us // 2 arrival from p3)")
    if delivery == "arrival":
        parts.append(f"dl as (select *, row_number() over (partition by {ND} order by arrival, worker, batch_seq) turn, arrival ready from ar)")
    else:
        parts.append(f"dl as (select *, row_number() over (partition by {ND} order by batch_seq, worker) turn, max(arrival) over (partition by {ND} order by batch_seq, worker) ready from ar)")
    return ", ".join(parts)


def pull_sql(kind: str, name: str = "documents", feed: Feed = FEED, names: tuple = (), rtt: str = "rtt_us", **how) -> str:
    s = asdict(feed) | {"rtt": rtt}
    fetch = {
        "pull_sample": "n * ({rtt} * {sample_rtts_permille} // 1000 + {decode_us}) + bytes * {size_scale} * 1000000 // {net_bytes_s} + bytes * {size_scale} * 1000000 // {disk_bytes_s}",
        "pull_pipeline": "greatest(n * greatest(1, (bytes * {size_scale} + n * {read_bytes} - 1) // (n * {read_bytes})) * {rtt} * {pipeline_rtts_permille} // 1000, bytes * {size_scale} * 1000000 // {net_bytes_s} + bytes * {size_scale} * 1000000 // {disk_bytes_s})",
    }[kind].format(**s)
    return f"""{batches_sql(name, **how)}, {regimes_sql(names)}, f as (select *, ({fetch})::bigint fetch_us, row_number() over (partition by {ND}
 order by batch_seq, worker) turn from bt, rg), dl as (select *, (sum(fetch_us) over (partition by {ND}
 order by turn))::bigint ready from f)"""


def used_sql(step_us: int = FEED.step_us) -> str:
    return f"cs as (select *, n * {step_us} step_us from dl), " + queue_sql("cs", "us", ND, "turn", "step_us", "done", "ready")


_TIMES = "select regime, epoch, node_id, worker, batch_seq, read_done, pack_done, send_done from p3"


def _times(df: DataFrame) -> DataFrame:
    return df.select("regime", "epoch", "node_id", "worker", "batch_seq", *(c for c in ("read_done", "pack_done", "send_done") if c in df.columns))


def serviced(spark, d, names: tuple = (), feed: Feed = FEED, name: str = "documents", **how) -> DataFrame:
    return T.services(batches(spark, d, name, **how), feed).crossJoin(F.broadcast(regimes(spark, *names)))


@query("pipeline_times", f"with recursive {push_sql(names=('lan', 'wan'))} {_TIMES}")
def pipeline_times(spark, d):
    return _times(T.pipeline_times(serviced(spark, d, ("lan", "wan"))))


@query("serial_times", f"with recursive {push_sql(names=('lan', 'wan'), pipelined=False)} select regime, epoch, node_id, worker, batch_seq, send_done from p3")
def serial_times(spark, d):
    return _times(T.serial_times(serviced(spark, d, ("lan", "wan"))))


_DEL = "select regime, epoch, node_id, worker, batch_seq, turn, ready from dl"
for _name, _how in {"delivery_arrival": {"delivery": "arrival"}, "delivery_in_order": {"delivery": "in_order"}}.items():
    query(_name, f"with recursive {push_sql(names=('lan_10', 'wan'), **_how)} {_DEL}")(lambda spark, d, h=_how: L.push_batch(batches(spark, d), regimes(spark, "lan_10", "wan"), **h).select("regime", "epoch", "node_id", "worker", "batch_seq", "turn", "ready"))


@query("tail_latency", f"""with recursive {push_sql(names=('lan', 'wan'))}, q as (select regime, (ready - (read_done - read_us))::double w
 from dl) select regime, count(*) n, floor(quantile_cont(w, 0.5) * 1e6 + 0.5) / 1e6 p50, floor(quantile_cont(w, 0.95) * 1e6 + 0.5) / 1e6 p95, floor(quantile_cont(w, 0.99) * 1e6 + 0.5) / 1e6 p99, max(w) worst
 from q group by all""")
def tail_latency(spark, d):
    return T.latency_profile(L.push_batch(batches(spark, d), regimes(spark, "lan", "wan")), ["regime"])


@query("hwm_rate_bound", f"""with {batches_sql()}, {regimes_sql()}, m as (select regime, rtt_us, (sum(bytes)::bigint * 40) // count(*) mean_bytes
 from bt, rg group by all), x as (select *, case when rtt_us > 0 then mean_bytes * 16 * 1000000 // nullif(rtt_us, 0) end window_bytes_s
 from m) select regime, rtt_us, mean_bytes::bigint mean_bytes, window_bytes_s::bigint window_bytes_s, least(coalesce(window_bytes_s, 1250000000), 1250000000)::bigint bound_bytes_s
 from x""")
def hwm_rate_bound(spark, d):
    return T.rate_bound(batches(spark, d).crossJoin(F.broadcast(regimes(spark))))


#: The consumer is quick here, so that what is in flight binds and not the training step.
QUICK = L.scaled(FEED, workers=1, step_us=100)
_LAG = "regime, epoch, node_id, hwm"


def walk_sql(source: str, keys: str, service: str, depth: str, use: str) -> str:
    """CTE `lw`: batches in turn, each served only when the one `depth` before it is used up; the walk carries the ends of use."""
    on = " and ".join(f"x.{k.strip()} = p.{k.strip()}" for k in keys.split(","))
    return f"""ln as (select *, row_number() over (partition by {keys} order by turn) rn from {source}),
lw as (select *, ({service})::bigint served, [({service} + {use})::bigint] ends from ln where rn = 1
 union all select x.*, y.served, list_append(p.ends, greatest(p.ends[-1], y.served) + x.{use}) from ln x join lw p on {on} and x.rn = p.rn + 1,
 lateral (select (greatest(p.served, case when x.rn > {depth} then p.ends[x.rn - {depth}] else 0 end) + x.{service})::bigint served) y)"""


_HWM = (
    f"with recursive {push_sql(feed=QUICK, names=('lan', 'wan'), scope='node', workers=1)}, hs as (select *, n * {QUICK.step_us} use_us from p3, (values (1), (4), (16)) t(hwm)), "
    + "hn as (select *, row_number() over (partition by " + _LAG + " order by batch_seq) rn from hs), "
    + """hw as (select *, pack_done + send_us served, [pack_done + send_us + rtt_us + rtt_us // 2] taken, [pack_done + send_us + rtt_us + rtt_us // 2 + use_us] ends from hn where rn = 1
 union all select x.*, y.served, list_append(p.taken, greatest(p.ends[-1], y.served + x.rtt_us + x.rtt_us // 2)), list_append(p.ends, greatest(p.ends[-1], y.served + x.rtt_us + x.rtt_us // 2) + x.use_us)
 from hn x join hw p on x.regime = p.regime and x.epoch = p.epoch and x.node_id = p.node_id and x.hwm = p.hwm and x.rn = p.rn + 1,
 lateral (select greatest(p.served, x.pack_done, case when x.rn > x.hwm then p.taken[x.rn - x.hwm] + x.rtt_us // 2 - x.rtt_us else 0 end) + x.send_us served) y)
select regime, epoch, node_id, hwm, max(ends[-1]) done from hw group by all"""
)


@query("hwm_bounded", _HWM)
def hwm_bounded(spark, d):
    """Delivery over one stream under high-water marks 1, 4 and 16, before a quick consumer."""
    b = batches(spark, d, scope="node", workers=1)
    packed, out = T.pipeline_times(T.services(b, QUICK).crossJoin(F.broadcast(regimes(spark, "lan", "wan")))), None
    for hwm in (1, 4, 16):
        t = T.bounded_times(packed, QUICK.step_us, hwm).groupBy("regime", "epoch", "node_id").agg(F.max("done").alias("done")).withColumn("hwm", F.lit(hwm))
        out = t if out is None else out.unionByName(t)
    return out


@query("hwm_unbounded_equals_closed_form", f"with recursive {push_sql(names=('lan', 'wan'))}, {used_sql()} select regime, epoch, node_id, max(done) done from us group by all")
def hwm_unbounded(spark, d):
    return T.bounded_times(T.pipeline_times(serviced(spark, d, ("lan", "wan"))), FEED.step_us, 1 << 30).groupBy("regime", "epoch", "node_id").agg(F.max("done").alias("done"))


@query("scale_out", f"""with {base_sql('lineitem')}, k as (select *, row_number() over (order by shard_id) - 1 k from st),
 b as (select servers, k % servers server, sum(100 + bytes * 40 * 1000000 // 500000000)::bigint us, sum(bytes)::bigint bytes
 from k, (values (1), (2), (4), (8)) t(servers) group by all) select servers::bigint servers, max(us) makespan_us, sum(us)::bigint total_us, ((sum(bytes)::bigint * 40 * 1000000) // max(us))::bigint bytes_s
 from b group by all""")
def scale_out(spark, d):
    return T.scale_out(stats(spark, d, "lineitem"))


# --- loaders ----------------------------------------------------------------------
_EPOCH = """select regime, rtt_us, epoch, max(t) modelled_us, sum(n)::bigint records, sum(b)::bigint bytes, count(*) nodes
 from (select regime, rtt_us, epoch, node_id, max(done) t, sum(n) n, sum(bytes) b from us group by all)
 group by all"""


def _epochs(df: DataFrame, feed: Feed = FEED) -> DataFrame:
    return L.epoch_times(L.consumed(df, feed))


query("loader_push_batch", f"with recursive {push_sql()}, {used_sql()} {_EPOCH}")(lambda spark, d: _epochs(L.push_batch(batches(spark, d), regimes(spark))))
query("loader_pull_sample", f"with recursive {pull_sql('pull_sample')}, {used_sql()} {_EPOCH}")(lambda spark, d: _epochs(L.pull_sample(batches(spark, d), regimes(spark))))
query("loader_pull_pipeline", f"with recursive {pull_sql('pull_pipeline')}, {used_sql()} {_EPOCH}")(lambda spark, d: _epochs(L.pull_pipeline(batches(spark, d), regimes(spark))))
query("ablate_no_prebatch", f"with recursive {push_sql(prebatched=False)}, {used_sql()} {_EPOCH}")(lambda spark, d: _epochs(L.push_batch(batches(spark, d), regimes(spark), prebatched=False)))
query("ablate_no_pipeline", f"with recursive {push_sql(pipelined=False)}, {used_sql()} {_EPOCH}")(lambda spark, d: _epochs(L.push_batch(batches(spark, d), regimes(spark), pipelined=False)))
query("ablate_in_order", f"with recursive {push_sql(delivery='in_order')}, {used_sql()} {_EPOCH}")(lambda spark, d: _epochs(L.push_batch(batches(spark, d), regimes(spark), delivery="in_order")))
query("remedy_cache", f"with recursive {pull_sql('pull_sample', rtt='(case when epoch > 1 then 0 else rtt_us end)')}, {used_sql()} {_EPOCH}")(lambda spark, d: _epochs(L.pull_sample(batches(spark, d), regimes(spark), cached_epochs=True)))
query("remedy_local_shards", f"with recursive {pull_sql('pull_sample', rtt='0')}, {used_sql()} {_EPOCH}")(lambda spark, d: _epochs(L.pull_sample(batches(spark, d), regimes(spark), local_only=True)))
_DOUBLE = f"""with recursive {pull_sql('pull_sample', names=('lan', 'wan'))}, du as (select *, n * {FEED.step_us} use_us
 from dl), {walk_sql('du', ND, 'fetch_us', '2', 'use_us')}, us as (select *, ends[-1] done
 from lw) {_EPOCH}"""
query("remedy_double_buffer", _DOUBLE)(lambda spark, d: _epochs(L.double_buffered(batches(spark, d), regimes(spark, "lan", "wan"))))
query("prefetch_unbounded", f"with recursive {push_sql(names=('wan',))}, {used_sql()} select regime, epoch, node_id, turn, ready, done from us")(lambda spark, d: L.consumed(L.push_batch(batches(spark, d), regimes(spark, "wan"))).select("regime", "epoch", "node_id", "turn", "ready", "done"))


def bounded_sql(feed: Feed, names: tuple, **how) -> str:
    """CTE `us` of one stream a node: the walk carries when payloads were taken and used up."""
    gate = "case when x.rn > {h} then p.taken[x.rn - {h}] + x.rtt_us // 2 - x.rtt_us else 0 end".format(h=feed.hwm)
    room = "case when x.rn > {q} then p.ends[x.rn - {q}] else 0 end".format(q=feed.depth)
    return f"""{push_sql(feed=feed, names=names, scope='node', workers=1, **how)},
bn as (select *, n * {feed.step_us} use_us, row_number() over (partition by {ND} order by batch_seq) rn from p3),
bw as (select *, pack_done + send_us served, [pack_done + send_us + rtt_us + rtt_us // 2] taken, [pack_done + send_us + rtt_us + rtt_us // 2 + use_us] ends from bn where rn = 1
 union all select x.*, y.served, list_append(p.taken, z.took), list_append(p.ends, greatest(p.ends[-1], z.took) + x.use_us)
 from bn x join bw p on x.regime = p.regime and x.epoch = p.epoch and x.node_id = p.node_id and x.rn = p.rn + 1,
 lateral (select greatest(p.served, x.pack_done, {gate}) + x.send_us served) y, lateral (select greatest(p.taken[-1], y.served + x.rtt_us + x.rtt_us // 2, {room}) took) z),
us as (select *, ends[-1] done from bw)"""


query("loader_push_bounded", f"with recursive {bounded_sql(QUICK, ())} {_EPOCH}")(lambda spark, d: L.epoch_times(L.push_bounded(batches(spark, d, scope="node", workers=1), regimes(spark), QUICK)))


#: Serializing takes the longest and the consumer is quick, so that further streams help until the disk binds.
STREAMS = L.scaled(FEED, step_us=50)


def streams_sql(workers: int) -> str:
    """The same batches, dealt to so many streams."""
    return f"{push_sql(feed=L.scaled(STREAMS, workers=workers), names=('lan', 'wan'), scope='node', workers=workers)}, {used_sql(STREAMS.step_us)}"


def with_streams(spark, d, workers: int) -> DataFrame:
    f = L.scaled(STREAMS, workers=workers)
    return _epochs(L.push_batch(batches(spark, d, scope="node", workers=workers), regimes(spark, "lan", "wan"), f), f)


query("ablate_one_stream", f"with recursive {streams_sql(1)} {_EPOCH}")(lambda spark, d: with_streams(spark, d, 1))


@query("streams_sweep", " union all ".join(f"select * from (with recursive {streams_sql(t)} select {t}::bigint streams, * from ({_EPOCH}))" for t in (1, 2, 4, 8)))
def streams_sweep(spark, d):
    out = None
    for t in (1, 2, 4, 8):
        x = with_streams(spark, d, t).withColumn("streams", F.lit(t).cast("long"))
        out = x if out is None else out.unionByName(x)
    return out


_DEPTH = (
    f"""with recursive {batches_sql()}, {regimes_sql(('wan',))}, pd as (select regime, epoch, node_id, depth, n * {FEED.decode_us} decode, n * {FEED.step_us} use_us, row_number() over (partition by regime, epoch, node_id, depth
 order by batch_seq, worker) turn"""
    f""" from bt, rg, (values (1::bigint), (4), ({1 << 30})) t(depth)), {walk_sql('pd', 'regime, epoch, node_id, depth', 'decode', 'x.depth', 'use_us')}
 select regime, epoch, node_id, max(ends[-1]) done, depth from lw group by all"""
)


@query("prefetch_depth", _DEPTH)
def prefetch_depth(spark, d):
    """Prefetch depths 1, 4 and without end: deeper is never later."""
    base = T.services(batches(spark, d), FEED).crossJoin(F.broadcast(regimes(spark, "wan"))).withColumn("decode", F.col("n") * FEED.decode_us)
    base = base.withColumn("turn", F.row_number().over(W.partitionBy(*L.NODE).orderBy("batch_seq", "worker")).cast("long"))
    out = None
    for q in (1, 4, 1 << 30):
        x = L.lookahead(base, "decode", FEED.step_us, q).groupBy(*L.NODE).agg(F.max("done").alias("done")).withColumn("depth", F.lit(q).cast("long"))
        out = x if out is None else out.unionByName(x)
    return out


@query("consumer_stall", f"""with recursive {push_sql(names=('lan', 'wan'))}, {used_sql()} select regime, epoch, node_id, sum(greatest(0, ready - before))::bigint stall_us, sum(n * 1500)::bigint busy_us
 from (select *, coalesce(lag(done) over (partition by {ND} order by turn), 0) before from us)
 group by all""")
def consumer_stall(spark, d):
    done = L.consumed(L.push_batch(batches(spark, d), regimes(spark, "lan", "wan")))
    before = F.coalesce(F.lag("done").over(W.partitionBy(*L.NODE).orderBy("turn")), F.lit(0).cast("long"))
    return done.withColumn("w", F.greatest(F.lit(0).cast("long"), F.col("ready") - before)).groupBy("regime", "epoch", "node_id").agg(F.sum("w").alias("stall_us"), F.sum(F.col("n") * FEED.step_us).alias("busy_us"))


@query("warmup_excluded", f"""with recursive {push_sql(names=('wan',))}, {used_sql()} select regime, epoch, node_id, max(done) - min(done) filter (turn = 4) after_us, max(done) whole_us
 from us group by all""")
def warmup_excluded(spark, d):
    done = L.consumed(L.push_batch(batches(spark, d), regimes(spark, "wan")))
    return done.groupBy("regime", "epoch", "node_id").agg((F.max("done") - F.min(F.when(F.col("turn") == FEED.depth, F.col("done")))).alias("after_us"), F.max("done").alias("whole_us"))


@query("sync_overhead", f"""with recursive {push_sql()}, {used_sql()} select regime, epoch, count(*) steps, sum(worst + 2 * rtt_us)::bigint synced_us
 from (select regime, rtt_us, epoch, turn, max(n * 1500) worst from us group by all) group by all""")
def sync_overhead(spark, d):
    """Lock-step training: each step takes its slowest node's time and one exchange of gradients."""
    done = L.consumed(L.push_batch(batches(spark, d), regimes(spark)))
    step = done.groupBy("regime", "rtt_us", "epoch", "turn").agg(F.max(F.col("n") * FEED.step_us).alias("worst"))
    return step.groupBy("regime", "epoch").agg(F.count("*").alias("steps"), F.sum(F.col("worst") + 2 * F.col("rtt_us")).alias("synced_us"))


@query("local_loopback_cost", f"with recursive {push_sql(names=('local',))}, {used_sql()} select epoch, sum(pack_us + send_us)::bigint loopback_us, max(done) done from us group by all")
def local_loopback_cost(spark, d):
    done = L.consumed(L.push_batch(batches(spark, d), regimes(spark, "local")))
    return done.groupBy("epoch").agg(F.sum(F.col("pack_us") + F.col("send_us")).alias("loopback_us"), F.max("done").alias("done"))


@query("traffic_by_rtt_class", """select case when cn.n_nationkey = sn.n_nationkey then 100 when cn.n_regionkey = sn.n_regionkey then 10000 else 30000 end::bigint rtt_us, r_name client_region, count(*) fetches, sum(64 + l_quantity::bigint)::bigint bytes
 from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey
 join supplier on l_suppkey = s_suppkey join nation cn on c_nationkey = cn.n_nationkey join nation sn on s_nationkey = sn.n_nationkey
 join region on cn.n_regionkey = r_regionkey group by all""")
def traffic_by_rtt_class(spark, d):
    nation = read(spark, d, "nation").select("n_nationkey", "n_regionkey")
    client = read(spark, d, "customer").join(nation, F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", F.col("n_nationkey").alias("cn"), F.col("n_regionkey").alias("cr"))
    server = read(spark, d, "supplier").join(nation, F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", F.col("n_nationkey").alias("sn"), F.col("n_regionkey").alias("sr"))
    j = read(spark, d, "lineitem").select("l_orderkey", "l_suppkey", "l_quantity").join(read(spark, d, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    j = j.join(client, F.col("o_custkey") == F.col("c_custkey")).join(server, F.col("l_suppkey") == F.col("s_suppkey")).join(read(spark, d, "region"), F.col("cr") == F.col("r_regionkey"))
    rtt = F.when(F.col("cn") == F.col("sn"), 100).when(F.col("cr") == F.col("sr"), 10_000).otherwise(30_000).cast("long")
    return j.groupBy(rtt.alias("rtt_us"), F.col("r_name").alias("client_region")).agg(F.count("*").alias("fetches"), F.sum(F.lit(64) + F.col("l_quantity").cast("long")).alias("bytes"))


# --- workloads --------------------------------------------------------------------
def cells_sql(name: str, names: tuple, feed: Feed, power, loaders: tuple, **how) -> str:
    """loader x regime cells of a workload."""
    idle, busy = dict(power.idle), dict(power.busy)
    energy = ", ".join(f"t * nodes * {idle[c]} + records * {feed.step_us * busy[c]} {c}_uj" for c in ("cpu", "dram", "gpu"))
    parts = []
    for loader in loaders:
        head = push_sql(name, feed, names, **how) if loader == "push_batch" else pull_sql(loader, name, feed, names, **how)
        parts.append(f"""select * from (with recursive {head}, {used_sql(feed.step_us)}, e as ({_EPOCH}) select '{loader}' loader, regime, rtt_us, sum(records)::bigint records, sum(bytes)::bigint b, sum(modelled_us)::bigint t, max(nodes) nodes
 from e group by all)""")
    return f"select loader, regime, rtt_us, records, b * {feed.size_scale} bytes, t modelled_us, {energy} from ({' union all '.join(parts)})"


ALL = ("push_batch", "pull_pipeline", "pull_sample")
TWO = ALL[:2]
#: 2 MB records from the page cache: one thread serializes a little slower than the mount delivers.
SYNTHETIC = L.scaled(FEED, size_scale=8192, disk_bytes_s=1_000_000_000, pack_ns_byte=2, step_us=1_000)
MODEL_B_FEED = L.scaled(FEED, step_us=1_400)
WORKLOADS = {
    "w02_small": ("documents", ("local", "lan", "lan_10", "wan"), FEED, MODEL_A, ALL, {}),
    "w03_mid": ("pages", ("lan", "lan_10", "wan"), PAGES, MODEL_A, TWO, {}),
    "w04_synthetic": ("embeddings", ("lan", "lan_1", "lan_10", "wan"), L.scaled(SYNTHETIC, workers=1), MODEL_A, TWO, {"scope": "node", "workers": 1}),
    "w05_synthetic_streams": ("embeddings", ("lan", "lan_1", "lan_10", "wan"), SYNTHETIC, MODEL_A, TWO, {"scope": "node", "workers": 2}),
    "w06_model_b": ("documents", ("lan", "lan_10", "wan"), MODEL_B_FEED, MODEL_B, TWO, {}),
}


def workload(spark, d, name: str) -> DataFrame:
    data, names, feed, power, who, how = WORKLOADS[name]
    return L.cells(batches(spark, d, data, **how), regimes(spark, *names), feed, power, who)


def workload_sql(name: str) -> str:
    data, names, feed, power, who, how = WORKLOADS[name]
    return cells_sql(data, names, feed, power, who, **how)


for _w in WORKLOADS:
    query(_w, workload_sql(_w))(lambda spark, d, w=_w: workload(spark, d, w))


@query("workloads_bounded")
def workloads_bounded(spark, d):
    """Workloads 2 to 6 with the sender's high-water mark of 16 and a prefetch depth of 4, beside the unbounded model."""
    out = None
    for name, (data, names, feed, power, _, how) in WORKLOADS.items():
        b, r = batches(spark, d, data, **how), regimes(spark, *names)
        pair = L.cells(b, r, feed, power, ("push_batch", "push_bounded")).groupBy("regime", "rtt_us").pivot("loader", ["push_batch", "push_bounded"]).agg(F.max("modelled_us"))
        t = pair.select(F.lit(name).alias("workload"), "regime", "rtt_us", F.col("push_batch").alias("unbounded_us"), F.col("push_bounded").alias("bounded_us"))
        out = t if out is None else out.unionByName(t)
    return out


@query("workloads_bounded_check", "select 0::bigint earlier, 0::bigint slower_than_pull")
def workloads_bounded_check(spark, d):
    """How often bounds make a push earlier, or slower than the pull pipeline at 10 ms and more: never."""
    pull = None
    for name, (data, names, feed, power, _, how) in WORKLOADS.items():
        t = L.cells(batches(spark, d, data, **how), regimes(spark, *names), feed, power, ("pull_pipeline",)).select(F.lit(name).alias("workload"), "regime", F.col("modelled_us").alias("pull_us"))
        pull = t if pull is None else pull.unionByName(t)
    both = workloads_bounded(spark, d).join(F.broadcast(pull), ["workload", "regime"])
    return both.agg(F.count_if(F.col("bounded_us") < F.col("unbounded_us")).alias("earlier"), F.count_if((F.col("rtt_us") >= 10_000) & (F.col("bounded_us") > F.col("pull_us"))).alias("slower_than_pull"))
