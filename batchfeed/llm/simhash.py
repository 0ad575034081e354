"""SimHash near-duplicates by deletion-variant signatures.

Fingerprints within two bits of each other are linked. A 64-bit fingerprint is cut
into two segments, so that one of them differs by at most one bit; every segment is
indexed under its 32 variants with one bit wildcarded. Fingerprints that share a
variant are candidates and are verified by counting differing bits.

A variant shared by more than `max_bucket` distinct fingerprints is not paired. Its
members go to an exact finer index: each is indexed under itself and its 64 one-bit
neighbours. Two fingerprints are within two bits just if they share such a neighbour,
and all that share one are linked, so each group is joined as a chain: linear work and
no link lost. Equal fingerprints are collapsed first, so copies cost one row.

Components come from hooking groups to each other with pointer jumping over distinct
fingerprints, each round written to the shared folder; rounds grow with the logarithm.

Edge cases: null and empty texts have fingerprint 0 and are linked like others; fewer
than three words make one shingle; rows with a null doc_id get the component of their
group, null if it has no other id; repeated rows fall into one component; `keep_first`
judges rows of one doc_id by their own texts and takes columns of any name.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window as W, functions as F

from .common import batches, free_name, texts, written


_NONE = (1 << 63) - 1


def fingerprint(text: bytes, width: int = 3, seed: int = 42) -> int:
    """Signed 64-bit SimHash: bit set where over half of the shingle hashes have it."""
    words = text.lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    if len(words) <= width:
        return int(np.array([xxhash.xxh64_intdigest(joined, seed)], np.uint64).view(np.int64)[0])
    lengths = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(lengths + 1) - 1
    starts = (ends - lengths)[: 1 - width].tolist()
    digest = xxhash.xxh64_intdigest
    h = np.fromiter([digest(joined[a:z], seed) for a, z in zip(starts, ends[width - 1 :].tolist())], np.uint64, len(starts))
    ones = np.zeros(64, np.int64)
    for i in range(0, len(h), 1 << 16):
        ones += np.unpackbits(h[i : i + (1 << 16), None].view(np.uint8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(h), bitorder="little").view(np.int64)[0])


def text_hash(text: Column) -> Column:
    """Tells the rows of one doc_id apart."""
    return F.xxhash64(F.coalesce(text, F.lit("")))


def fingerprints(docs: DataFrame, width: int = 3, seed: int = 42) -> DataFrame:
    """doc_id, text_hash and `fp` (signed long) of every row."""

    def run(rows):
        for batch in batches(rows, 8 << 20):
            fp = [fingerprint(t, width, seed) for t in texts(batch["text"])]
            yield pa.RecordBatch.from_arrays([batch["doc_id"], batch["text_hash"], pa.array(fp, pa.int64())], ["doc_id", "text_hash", "fp"])

    return docs.select(F.col("doc_id").cast("long"), text_hash(F.col("text")).alias("text_hash"), "text").mapInArrow(run, "doc_id long, text_hash long, fp long")


def segment_variants(fp: Column) -> Column:
    """64 keys: (segment, wildcard bit, the segment with that bit cleared) packed in a long."""
    low = fp.bitwiseAND(F.lit(0xFFFFFFFF).cast("long"))
    high = F.shiftrightunsigned(fp, 32)

    def keys(segment: Column, number: int) -> Column:
        return F.transform(F.sequence(F.lit(0), F.lit(31)), lambda i: F.lit(number << 37).cast("long") + F.call_function("shiftleft", i.cast("long"), F.lit(32)) + segment.bitwiseAND(F.bitwise_not(F.call_function("shiftleft", F.lit(1).cast("long"), i))))

    return F.concat(keys(low, 0), keys(high, 1))


def neighbours(fp: Column) -> Column:
    """fp and its 64 one-bit neighbours."""
    return F.concat(F.array(fp), F.transform(F.sequence(F.lit(0), F.lit(63)), lambda i: fp.bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("long"), i))))


def links(fps: DataFrame, max_bucket: int = 24) -> DataFrame:
    """Verified links a < b between the distinct values of fps(fp), enough to join all that are within two bits."""
    indexed = fps.select("fp", F.explode(segment_variants(F.col("fp"))).alias("key"))
    sized = indexed.withColumn("n", F.count("*").over(W.partitionBy("key"))).where("n > 1")
    shared = written(sized, "variants")
    few = shared.where(F.col("n") <= max_bucket)
    left, right = few.select("key", F.col("fp").alias("a")), few.select("key", F.col("fp").alias("b"))
    paired = left.join(right, "key").where("a < b").where(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= 2).select("a", "b")
    many = shared.where(F.col("n") > max_bucket).select("fp").distinct()
    near = many.select("fp", F.explode(neighbours(F.col("fp"))).alias("key"))
    chained = near.select(F.lag("fp").over(W.partitionBy("key").orderBy("fp")).alias("a"), F.col("fp").alias("b")).where("a IS NOT NULL")
    return paired.unionByName(chained).distinct()


def components(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """fp, label (the least `low`) and root (the fp that has it) of each component; nodes(fp, low), edges(a, b).

    Every round hooks each group of nodes under one label to the least other label next
    to any of its members, roots too. Two groups that chose each other are the only loops
    and the lesser of them is the root, which is also the least of its tree. Pointer
    jumping then relabels the groups by their roots. Each group with a link to another
    merges, so these at least halve in every round; it ends when none is left.
    Only nodes with a link take part.
    """
    linked = edges.select(F.col("a").alias("fp")).unionByName(edges.select(F.col("b").alias("fp"))).distinct()
    # labels are ranks (low, fp), so that equal or null lows of different nodes stay apart
    label = written(nodes.join(linked, "fp", "left_semi").select("fp", F.struct(F.coalesce("low", F.lit(_NONE)).alias("low"), F.col("fp").alias("id")).alias("label")), "labels")
    between = edges.select("a", "b")
    while True:
        la, lb = label.select(F.col("fp").alias("a"), F.col("label").alias("x")), label.select(F.col("fp").alias("b"), F.col("label").alias("y"))
        open_ = written(between.join(la, "a").join(lb, "b").where("x != y").select("a", "b", "x", "y"), "open")
        if open_.isEmpty():
            return label.select("fp", F.col("label.low").alias("label"), F.col("label.id").alias("root"))
        between = open_.select("a", "b")
        sides = open_.select("x", "y").unionByName(open_.select(F.col("y").alias("x"), F.col("x").alias("y")))
        near = written(sides.groupBy("x").agg(F.min("y").alias("y")), "near")
        back = near.select(F.col("x").alias("y"), F.col("y").alias("_back"))
        hook = near.join(back, "y").select("x", F.when((F.col("_back") == F.col("x")) & (F.col("x") < F.col("y")), F.col("x")).otherwise(F.col("y")).alias("y"))
        hook = written(hook, "hooks")
        while True:
            up = hook.select(F.col("x").alias("y"), F.col("y").alias("_up"))
            step = written(hook.join(up, "y").select("x", F.col("y").alias("_old"), F.col("_up").alias("y")), "hooks")
            settled = step.where("y != _old").isEmpty()
            hook = step.select("x", "y")
            if settled:
                break
        label = written(label.join(hook, F.col("label") == F.col("x"), "left").select("fp", F.coalesce("y", "label").alias("label")), "labels")


def clustered(docs: DataFrame, max_bucket: int = 24) -> DataFrame:
    """doc_id, text_hash, fp, component_id and root (a fingerprint that names the component) of every row."""
    printed = written(fingerprints(docs), "fingerprints")
    nodes = written(printed.groupBy("fp").agg(F.min("doc_id").alias("low")), "nodes")
    label = components(nodes, links(nodes.select("fp"), max_bucket))
    final = nodes.join(label, "fp", "left").select("fp", F.when(F.col("label") < _NONE, F.col("label")).otherwise(F.col("low")).alias("component_id"), F.coalesce("root", "fp").alias("root"))
    return printed.join(final, "fp").select("doc_id", "text_hash", "fp", "component_id", "root")


def near_duplicates(docs: DataFrame, max_bucket: int = 24) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id of every row of docs(doc_id, text)."""
    return clustered(docs, max_bucket).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_first(docs: DataFrame, broadcast_rows: int = 1_000_000, **options) -> DataFrame:
    """One row of each component, that of its smallest doc_id (null last), with the columns of docs.

    Of rows with that doc_id the one with the least hash of its text stays. The rows that
    go are listed by (doc_id, hash of the text), a narrow list, and anti-joined: broadcast
    if it is counted to have at most broadcast_rows rows of 16 bytes, else by a hash join
    on that side, so that the texts are never sorted.
    """
    found = written(clustered(docs, **options).select("doc_id", "text_hash", "root"), "clusters")
    rank = F.struct(F.coalesce("doc_id", F.lit(_NONE)).alias("i"), F.col("doc_id").isNull().alias("z"), F.col("text_hash").alias("h"))
    several = written(found.groupBy("root").agg(F.min(rank).alias("least"), F.count("*").alias("n")).where("n > 1").drop("n"), "several")
    member = found.join(several, "root").withColumn("rank", rank)
    gone = written(member.where("rank != least").select("doc_id", "text_hash").distinct(), "gone")
    again = member.where("rank = least").groupBy("doc_id", "text_hash").agg(F.count("*").alias("n")).where("n > 1").select("doc_id", "text_hash")
    name = {c: free_name(docs, c) for c in ("doc", "text_hash", "place")}
    cols = [f"`{c}`" for c in docs.columns]

    def near(keys: DataFrame) -> tuple:
        keys = keys.select(F.col("doc_id").alias(name["doc"]), F.col("text_hash").alias(name["text_hash"]))
        return (F.broadcast(keys) if keys.count() <= broadcast_rows else keys.hint("shuffle_hash")), F.col("doc_id").cast("long").eqNullSafe(F.col(name["doc"])) & (text_hash(F.col("text")) == F.col(name["text_hash"]))

    kept = docs.join(*near(gone), "left_anti")
    again = written(again, "again")
    if again.isEmpty():
        return kept
    # rows alike in doc_id and text: one of each
    keys, same = near(again)
    once = kept.join(keys, same, "left_anti")
    place = F.row_number().over(W.partitionBy(F.col("doc_id"), F.col("text")).orderBy(F.lit(1)))
    return once.unionByName(kept.join(keys, same, "left_semi").withColumn(name["place"], place).where(F.col(name["place"]) == 1).select(*cols))
