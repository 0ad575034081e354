"""Planner: shard order, dealing to nodes and workers, and batches of contiguous ranges.

Plans come from shard counts; records are never exploded. A plan row is a range:
epoch, node_id, worker, batch_seq, shard_id, first_ordinal, n.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window as W, functions as F

from ..config import FEED
from ..functions.columns import div


def shuffle_shards(stats: DataFrame, epochs: int, seed: int = FEED.seed) -> DataFrame:
    """epoch, shard_id, n, k: the shards of each epoch in the order of a seeded digest."""
    e = stats.select("shard_id", "n", F.explode(F.sequence(F.lit(1), F.lit(epochs))).alias("epoch"))
    key = F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("epoch").cast("string"), "shard_id"))
    return e.withColumn("k", (F.row_number().over(W.partitionBy("epoch").orderBy(key, "shard_id")) - 1).cast("long"))


def assign_nodes(order: DataFrame, n_nodes: int, coverage: str = "partition") -> DataFrame:
    """Add node_id and pos, the shard's place on its node. replicate: every node gets all."""
    if coverage == "replicate":
        return order.withColumn("node_id", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n_nodes - 1).cast("long")))).withColumn("pos", F.col("k"))
    return order.withColumn("node_id", F.col("k") % n_nodes).withColumn("pos", div(F.col("k"), n_nodes))


def assign_workers(assigned: DataFrame, workers: int, split: str = "striped") -> DataFrame:
    """Add worker, first and count (the range of the shard it reads)."""
    whole = [F.lit(0).cast("long").alias("first"), F.col("n").alias("count")]
    if split == "striped":
        return assigned.select("*", (F.col("pos") % workers).alias("worker"), *whole)
    if split == "chunked":
        w = W.partitionBy("epoch", "node_id").orderBy("pos")
        return assigned.select("*", (F.ntile(workers).over(w) - 1).cast("long").alias("worker"), *whole)
    if split == "intra_shard":
        t = assigned.withColumn("worker", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(workers - 1).cast("long"))))
        low, more = div(F.col("n"), workers), F.col("n") % workers
        first = F.col("worker") * low + F.least("worker", more)
        return t.select("*", first.alias("first"), (low + (F.col("worker") < more).cast("long")).alias("count")).where("count > 0")
    raise ValueError(split)


def batch_plan(work: DataFrame, batch: int = FEED.batch, scope: str = "shard", tail: str = "keep", workers: int = FEED.workers) -> DataFrame:
    """Cut work into batches.

    scope shard: batches end with their shard; worker or node: they run over the shards of a
    worker or node (node: batches are dealt to workers in turn). tail: keep, drop_last or
    pad (adds `padded`, records repeated to fill a batch).
    """
    if scope == "shard":
        # numbered by shard, before the shards are cut: the window sees one row a shard range
        line = W.partitionBy("epoch", "node_id", "worker").orderBy("pos", "first").rowsBetween(W.unboundedPreceding, -1)
        some = work.where("count > 0").withColumn("_many", div(F.col("count") + (batch - 1), batch))
        some = some.withColumn("_before", F.coalesce(F.sum("_many").over(line), F.lit(0).cast("long")))
        parts = some.withColumn("j", F.explode(F.sequence(F.lit(0).cast("long"), F.col("_many") - 1)))
        rows = parts.select("epoch", "node_id", "worker", (F.col("_before") + F.col("j")).alias("batch_seq"), "shard_id", (F.col("first") + F.col("j") * batch).alias("first_ordinal"), F.least(F.lit(batch).cast("long"), F.col("count") - F.col("j") * batch).alias("n"))
    else:
        keys = ["epoch", "node_id", "worker"] if scope == "worker" else ["epoch", "node_id"]
        line = W.partitionBy(*keys).orderBy("pos", "first").rowsBetween(W.unboundedPreceding, -1)
        laid = work.where("count > 0").withColumn("o", F.coalesce(F.sum("count").over(line), F.lit(0).cast("long")))
        cells = laid.withColumn("b", F.explode(F.sequence(div(F.col("o"), batch), div(F.col("o") + F.col("count") - 1, batch))))
        a, z = F.greatest(F.col("o"), F.col("b") * batch), F.least(F.col("o") + F.col("count"), (F.col("b") + 1) * batch)
        worker = F.col("worker") if scope == "worker" else F.col("b") % workers
        rows = cells.select("epoch", "node_id", worker.alias("worker"), F.col("b").alias("batch_seq"), "shard_id", (F.col("first") + a - F.col("o")).alias("first_ordinal"), (z - a).alias("n"))
    if tail == "keep":
        return rows
    size = F.sum("n").over(W.partitionBy("epoch", "node_id", "worker", "batch_seq"))
    if tail == "drop_last":
        return rows.withColumn("_size", size).where(F.col("_size") == batch).drop("_size")
    if tail == "pad":
        return rows.withColumn("padded", F.lit(batch) - size)
    raise ValueError(tail)


def equalize(plan: DataFrame, mode: str) -> DataFrame:
    """Give every node of an epoch as many batches: truncate to the least, or repeat to the most.

    Steps of a node: its batches by (batch_seq, worker). Adds step and is_repeat.
    """
    b = plan.groupBy("epoch", "node_id", "worker", "batch_seq").agg(F.sum("n").alias("n"))
    step = (F.row_number().over(W.partitionBy("epoch", "node_id").orderBy("batch_seq", "worker")) - 1).cast("long")
    b = b.withColumn("step", step).withColumn("own", F.count("*").over(W.partitionBy("epoch", "node_id")))
    w = W.partitionBy("epoch")
    if mode == "truncate":
        return b.withColumn("m", F.min("own").over(w)).where("step < m").drop("m", "own").withColumn("is_repeat", F.lit(False))
    if mode == "repeat":
        b = b.withColumn("m", F.max("own").over(w)).withColumn("again", F.explode(F.sequence(F.lit(0).cast("long"), div(F.col("m") - 1 - F.col("step"), F.col("own")))))
        return b.withColumn("step", F.col("step") + F.col("again") * F.col("own")).where("step < m").withColumn("is_repeat", F.col("again") > 0).drop("m", "own", "again")
    return b.drop("own").withColumn("is_repeat", F.lit(False))


def check_plan(plan: DataFrame, stats: DataFrame, batch: int, coverage: str = "partition") -> DataFrame:
    """Violations: kind, epoch, shard_id, n. Empty for a right plan."""
    keys = ["epoch", "shard_id"] + (["node_id"] if coverage == "replicate" else [])
    w = W.partitionBy(*keys).orderBy("first_ordinal")
    r = plan.withColumn("_next", F.lead("first_ordinal").over(w)).withColumn("_end", F.col("first_ordinal") + F.col("n"))
    overlap = r.where("_next < _end").select(F.lit("overlap").alias("kind"), "epoch", "shard_id", "n")
    gap = r.where("_next > _end").select(F.lit("gap").alias("kind"), "epoch", "shard_id", "n")
    covered = plan.groupBy(*keys).agg(F.sum("n").alias("n"), F.min("first_ordinal").alias("a"))
    epochs = plan.select("epoch").distinct()
    runs = plan.select("epoch", "node_id").distinct() if coverage == "replicate" else epochs  # one row an epoch (and node)
    short = stats.select("shard_id", F.col("n").alias("_n")).where("_n > 0").join(F.broadcast(runs)).join(covered, keys, "left").where("n IS NULL OR n <> _n OR a <> 0").select(F.lit("coverage").alias("kind"), "epoch", "shard_id", F.col("_n").alias("n"))
    large = plan.groupBy("epoch", "node_id", "worker", "batch_seq").agg(F.sum("n").alias("n")).where(F.col("n") > batch).select(F.lit("large").alias("kind"), "epoch", F.lit(None).cast("string").alias("shard_id"), "n")
    return overlap.unionByName(gap).unionByName(short).unionByName(large)


def with_bytes(plan: DataFrame, index: DataFrame, header: int = FEED.header) -> DataFrame:
    """Add byte_start and byte_end of each range by two lookups in the index."""
    a = index.select("shard_id", F.col("ordinal").alias("first_ordinal"), F.col("offset").alias("byte_start"))
    z = index.select("shard_id", F.col("ordinal").alias("_last"), (F.col("offset") + F.col("size") + header).alias("byte_end"))
    return plan.withColumn("_last", F.col("first_ordinal") + F.col("n") - 1).join(a, ["shard_id", "first_ordinal"]).join(z, ["shard_id", "_last"]).drop("_last")


def batches(ranged: DataFrame) -> DataFrame:
    """One row per batch: n, bytes and number of ranges."""
    return ranged.groupBy("epoch", "node_id", "worker", "batch_seq").agg(F.sum("n").alias("n"), F.sum(F.col("byte_end") - F.col("byte_start")).alias("bytes"), F.count("*").alias("n_ranges"))


def expected_batches(stats: DataFrame, batch: int) -> DataFrame:
    """Batch counts by the laws: per shard, and of one undivided run."""
    up = lambda x: div(x + (batch - 1), batch)
    return stats.agg(F.sum(up(F.col("n"))).alias("by_shard"), up(F.sum("n")).alias("by_node"))


def place_shards(stats: DataFrame, servers: int, how: str = "modulo") -> DataFrame:
    """shard_id, server: modulo of the shard's rank, or snake order by bytes to balance them."""
    if how == "modulo":
        return stats.withColumn("server", (F.row_number().over(W.orderBy("shard_id")) - 1).cast("long") % servers)
    k = (F.row_number().over(W.orderBy(F.desc("bytes"), "shard_id")) - 1).cast("long")
    t = stats.withColumn("_k", k)
    r = F.col("_k") % (2 * servers)
    return t.withColumn("server", F.when(r < servers, r).otherwise(2 * servers - 1 - r)).drop("_k")


def locality(plan: DataFrame, placed: DataFrame) -> DataFrame:
    """Records and ranges per node read from its own server and from others."""
    j = plan.join(placed.select("shard_id", "server"), "shard_id")
    return j.withColumn("is_local", F.col("server") == F.col("node_id")).groupBy("epoch", "node_id", "is_local").agg(F.sum("n").alias("records"), F.count("*").alias("ranges"))


def record_shuffle(index: DataFrame, buffer: int, seed: int = FEED.seed) -> DataFrame:
    """Order records at random within blocks of `buffer` successive ones of a shard."""
    key = F.md5(F.concat_ws(":", F.lit(str(seed)), "shard_id", F.col("ordinal").cast("string")))
    block = div(F.col("ordinal"), buffer)
    place = F.row_number().over(W.partitionBy("shard_id", block).orderBy(key, "ordinal")) - 1 + block * buffer
    return index.select("shard_id", "ordinal", place.cast("long").alias("place"))
