"""Katz backoff language model over n-grams of words.

Texts are lower-cased (A-Z) and cut at white space; an end token closes each. Counts
are of training documents only. Counts r up to `reliable` are discounted by
Good-Turing, larger ones by a fixed 0.05 of a count, so that every context keeps mass
for backing off. N-grams of order 2 and up need `least_count` occurrences to be kept,
Katz's cut of the rarest. What discounts and the cut leave is given to the lower order
over the words not seen, by weights that make each context's probabilities sum to one; the
unigrams' rest is the probability of an unknown word.

Counting and scoring go through `key_exchange`: blocks of documents ask for the counts
of all their n-grams at once, then for the backoff weights of the contexts they need,
and score their tokens from the highest order down. Frequent n-grams thus cost an
entry per block, and no table is broadcast. The backoff weights are kept in a
partitioned table, and `ngram_table` writes the counts likewise.

Edge cases: null and empty texts are the end token alone; without training documents
every token is unknown with probability one; a null doc_id is in the bucket of the
empty text; repeated rows count and are scored each.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .common import crc_bucket, mixed, new_path, word_hashes, written
from .key_exchange import ASK_SCHEMA, Block, Exchange, answered, asked, block_rows, blocks, cut, joined, looked_up, meet, packed, unpacked, values_in_order

_BOS, _END = word_hashes([b"\x20bos", b"\x20end"])
_LARGE_DISCOUNT = 0.05


class BlockGrams:
    """n-grams of a block: padded tokens, keys of each order, and the distinct keys."""

    def __init__(self, block: Block, order: int, folds: int, held: int):
        self.order = order
        pad = max(order - 1, 1)
        starts = np.full(pad, _BOS)
        end = np.array([_END])
        split = [t.lower().split() for t in block.texts]
        self.sizes = np.array([len(w) + 1 for w in split], np.int64)
        self.tokens = np.concatenate([x for w in split for x in (starts, word_hashes(w), end)] or [np.zeros(0, np.uint64)])
        whole = self.sizes + pad
        self.place = np.arange(len(self.tokens)) - np.repeat(np.cumsum(whole) - whole, whole)
        self.real = self.place >= pad
        self.doc = np.repeat(np.arange(len(split)), whole)
        buckets = [crc_bucket(None if z else int(i), folds) for i, z in zip(block.doc_ids, block.doc_null, strict=True)]
        self.held_out = np.array([b == held for b in buckets], bool)
        train = ~self.held_out[self.doc] if len(self.doc) else np.zeros(0, bool)
        self.keys = []
        for m in range(1, order + 1):
            salt = np.uint64(m * 0x51_7C_C1_B7_27_22_0A_95 & (1 << 64) - 1)
            before = np.roll(self.keys[-1], 1) if m > 1 else np.zeros(len(self.tokens), np.uint64)
            self.keys.append(mixed(before ^ salt, self.tokens))
        valid = [(self.place >= m - 1) & (self.real | (m < max(order, 2))) for m in range(1, order + 1)]
        where = np.concatenate([np.flatnonzero(v) for v in valid])
        orders = np.repeat(np.arange(order), [v.sum() for v in valid])
        flat = np.concatenate([k[v] for k, v in zip(self.keys, valid, strict=True)])
        self.distinct, inverse = np.unique(flat, return_inverse=True)
        self.at = np.full((order, len(self.tokens)), -1, np.int64)
        self.at[orders, where] = inverse
        self.count = np.bincount(inverse, train[where], len(self.distinct)).astype(np.uint32)
        self.kind = np.zeros(len(self.distinct), np.uint8)
        self.kind[inverse] = np.where(self.real[where], orders + 1, 0)
        self.first = np.zeros(len(self.distinct), np.int64)
        self.first[inverse[::-1]] = where[::-1]


@dataclass
class Totals:
    """Counts of counts by order (0 for the pads): numbers of n-grams seen r times, and the rest."""

    n_r: np.ndarray
    above: np.ndarray
    above_sum: np.ndarray
    tokens: int
    types: int

    def discounts(self, order: int, reliable: int) -> np.ndarray:
        """Share that is kept of counts 0..reliable."""
        n = self.n_r[order].astype(float)
        d = np.array([0.0, *(max(r - 0.5, 0.05) / r for r in range(1, reliable + 1))])
        if n[1] > 0:
            cap = (reliable + 1) * (n[reliable + 1]) / n[1]
            for r in range(1, reliable + 1):
                if n[r] > 0 and n[r + 1] > 0 and cap < 1:
                    good = ((r + 1) * n[r + 1] / n[r] / r - cap) / (1 - cap)
                    if 0.01 < good < 0.999:
                        d[r] = good
        return d

    def kept_counts(self, order: int, count: np.ndarray, reliable: int) -> np.ndarray:
        """Discounted counts."""
        d = self.discounts(order, reliable)
        return np.where(count > reliable, count - _LARGE_DISCOUNT, count * d[np.minimum(count, reliable)])

    def unknown(self, reliable: int) -> float:
        """Probability left for unknown words."""
        if not self.tokens:
            return 1.0
        kept = sum(self.n_r[1][r] * r * d for r, d in enumerate(self.discounts(1, reliable))) + self.above_sum[1] - _LARGE_DISCOUNT * self.above[1]
        return (self.tokens - kept) / self.tokens  # over 0, since each type keeps less than its count


def _answer(reliable: int, orders: int):
    def run(keys, place, values):
        count, kind = values
        total = np.bincount(place, count, len(keys)).astype(np.uint32)
        kinds = np.zeros(len(keys), np.int64)
        kinds[place] = kind
        owner = np.zeros(len(place), np.uint8)
        owner[np.unique(place, return_index=True)[1]] = 1
        stats = np.zeros((orders + 1, reliable + 4), np.int64)
        for o in range(orders + 1):
            mine = total[kinds == o].astype(np.int64)
            stats[o, : reliable + 2] = np.bincount(np.minimum(mine, reliable + 2), minlength=reliable + 3)[: reliable + 2]
            stats[o, 0] = mine.sum()
            big = mine[mine > reliable]
            stats[o, reliable + 2], stats[o, reliable + 3] = len(big), big.sum()
        return [total[place], owner], [stats.ravel()]

    return run


class _Scorer:
    """Probabilities of a block's tokens from the answered counts."""

    def __init__(self, grams: BlockGrams, answers: list[np.ndarray], totals: Totals, reliable: int, least: int):
        self.g = grams
        counts, self.owner = answers
        self.total = counts.astype(np.int64)
        self.c = np.where(grams.at >= 0, self.total[np.maximum(grams.at, 0)], 0)
        self.kept = [self.c[m] >= (1 if m == 0 else least) for m in range(grams.order)]
        n = max(totals.tokens, 1)
        unknown = totals.unknown(reliable)
        self.p = [np.where(self.c[0] > 0, totals.kept_counts(1, self.c[0], reliable) / n, unknown)]
        for m in range(1, grams.order):
            context = np.roll(self.c[m - 1], 1)
            self.p.append(np.where(self.kept[m], totals.kept_counts(m + 1, self.c[m], reliable) / np.maximum(context, 1), 0.0))


def _totals(answers: DataFrame, orders: int, reliable: int) -> Totals:
    """Sum the stats rows: one of a few dozen numbers per key partition, added up in Spark."""
    width = (orders + 1) * (reliable + 4)

    def numbers(rows):
        for batch in rows:
            for load in batch["payload"].to_pylist():
                yield pa.RecordBatch.from_arrays([pa.array(range(width), pa.int32()), pa.array(unpacked(cut(load)[0]), pa.int64())], ["i", "v"])

    sums = answers.where("block < 0").select("payload").mapInArrow(numbers, "i int, v long").groupBy("i").agg(F.sum("v").alias("v")).collect()
    s = np.zeros(width, np.int64)
    for r in sums:
        s[r.i] = r.v
    s = s.reshape(orders + 1, -1)
    types = int(s[1, 1 : reliable + 1].sum() + s[1, reliable + 2])
    n_r = s[:, : reliable + 2].copy()
    n_r[:, 0] = 0
    return Totals(n_r, s[:, reliable + 2], s[:, reliable + 3], int(s[1, 0]), types)


def score(docs: DataFrame, order: int = 2, folds: int = 10, held: int = 0, reliable: int = 5, least_count: int = 2, base_add: float = 0.1, block_bytes: int = 3 << 20, part_bytes: int = 5 << 20, fan: int = 4096) -> DataFrame:
    """Score every row of docs(doc_id, text) by a model of those whose bucket is not held.

    Returns doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score (log10).
    """
    packed_docs = blocks(docs, block_bytes)
    exchange = Exchange.over(packed_docs, part_bytes, fan)

    def first(rows):
        for batch in rows:
            for block in block_rows(batch):
                g = BlockGrams(block, order, folds, held)
                yield asked(block, g.distinct, [g.count, g.kind], exchange)

    counted = written(answered(packed_docs.mapInArrow(first, ASK_SCHEMA), exchange, _answer(reliable, order)), "counts")
    exchange.release(docs.sparkSession)
    totals = _totals(counted, order, reliable)
    base_all = math.log10(totals.tokens + base_add * (totals.types + 1))

    def evaluate(block: Block, got: dict) -> pa.Table:
        g = BlockGrams(block, order, folds, held)
        s = _Scorer(g, got[0], totals, reliable, least_count)
        real = g.real
        # backoff sums of the n-grams that this block answers for
        rows = []
        for m in range(1, order):
            mine = np.flatnonzero((g.kind == m + 1) & (s.owner > 0) & (s.total >= least_count))
            at = g.first[mine]
            context = np.roll(g.keys[m - 1], 1)[at]
            keys, place = np.unique(context, return_inverse=True)
            rows.append((keys, np.bincount(place, s.p[m][at], len(keys)).astype(float), np.bincount(place, s.p[m - 1][at], len(keys)).astype(float)))
        # tokens from the highest order down: what is not kept backs off by its context's weight
        log_p = np.zeros(len(g.tokens))
        open_ = real.copy()
        ask_context, ask_doc = [], []
        for m in range(order - 1, 0, -1):
            hit = open_ & s.kept[m]
            log_p[hit] = np.log10(s.p[m][hit])
            open_ &= ~hit
            back = np.flatnonzero(open_ & (np.roll(s.c[m - 1], 1) >= least_count))
            ask_context.append(np.roll(g.keys[m - 1], 1)[back])
            ask_doc.append(g.doc[back])
        log_p[open_] = np.log10(s.p[0][open_])
        n = len(g.sizes)
        per_doc = lambda w: np.bincount(g.doc[real], w[real], n).astype(float)
        keys, place = np.unique(np.concatenate([*ask_context, np.zeros(0, np.uint64)]), return_inverse=True)
        pairs, times = np.unique(np.concatenate([*ask_doc, np.zeros(0, np.int64)]).astype(np.uint64) << np.uint64(32) | place.astype(np.uint64), return_counts=True)
        state = joined([
            packed(np.asarray(block.doc_ids, "<i8")), packed(block.doc_null.astype(np.uint8)), packed(g.held_out.astype(np.uint8)), packed(g.sizes), packed(per_doc((s.c[0] > 0).astype(float)).astype(np.int64)),
            packed(per_doc(np.log10(s.c[0] + base_add)) - g.sizes * base_all), packed(per_doc(log_p)),
            packed(np.bincount((pairs >> np.uint64(32)).astype(np.int64), minlength=n)), packed((pairs & np.uint64(0xFFFFFFFF)).astype(np.uint32)), packed(times.astype(np.uint32)),
        ])
        asks = asked(block, keys, [], exchange)
        context = np.concatenate([r[0] for r in rows] or [np.zeros(0, np.uint64)])
        sums = [np.concatenate([r[i] for r in rows] or [np.zeros(0)]) for i in (1, 2)]
        orders = np.concatenate([np.full(len(r[0]), m + 2, np.int32) for m, r in enumerate(rows)] or [np.zeros(0, np.int32)])
        k, a = asks.num_rows, len(context)
        return pa.table({
            "kind": pa.array(["state"] + ["ask"] * k + ["weight"] * a), "part": pa.concat_arrays([pa.array([0], pa.int32()), asks["part"], pa.array(orders, pa.int32())]),
            "block": pa.array(np.full(1 + k + a, block.number)), "crc": pa.array(np.full(1 + k + a, block.crc)),
            "payload": pa.concat_arrays([pa.array([state], pa.binary()), asks["payload"], pa.nulls(a, pa.binary())]),
            "key": pa.concat_arrays([pa.nulls(1 + k, pa.int64()), pa.array(context.view(np.int64))]),
            "kept": pa.concat_arrays([pa.nulls(1 + k, pa.float64()), pa.array(sums[0])]), "lower": pa.concat_arrays([pa.nulls(1 + k, pa.float64()), pa.array(sums[1])]),
        })

    made = written(meet(packed_docs, counted.withColumn("level", F.lit(0)), evaluate, "kind string, part int, block long, crc long, payload binary, key long, kept double, lower double"), "evaluated", partition_by=("kind",))
    exchange.release(docs.sparkSession)
    weights = backoff_table(made.where("kind = 'weight'").select(F.col("part").alias("order"), "key", "kept", "lower"))
    asks = made.where("kind = 'ask'").select("part", "block", "crc", "payload")
    answers = looked_up(asks, weights, exchange)
    states = made.where("kind = 'state'").select("block", "crc", "payload")

    def finish(left: pa.Table, right: pa.Table) -> pa.Table:
        out, got = [], right.to_pylist()
        for row in left.to_pylist():
            ids, null, held_out, sizes, known, base, part_score, pairs, place, times = (unpacked(x) for x in cut(row["payload"]))
            log_w = (values_in_order(got, row["crc"]) or [np.zeros(1)])[0]
            doc = np.repeat(np.arange(len(sizes)), pairs)
            more = np.bincount(doc, log_w[place] * times, len(sizes)) if len(place) else np.zeros(len(sizes))
            out.append(pa.table({"doc_id": pa.array(ids, pa.int64(), mask=null.astype(bool)), "held_out": pa.array(held_out.astype(bool)), "n_tokens": pa.array(sizes, pa.int64()), "n_known": pa.array(known, pa.int64()), "train_tokens": pa.array(np.full(len(sizes), totals.tokens), pa.int64()), "base_score": pa.array(base), "score": pa.array(part_score + more)}))
        return pa.concat_tables(out)

    return states.groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(finish, "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")


def backoff_table(parts: DataFrame) -> DataFrame:
    """key, value: log10 backoff weight of every context with kept n-grams; stored by order.

    parts(order, key, kept, lower): partial sums of kept and of lower-order probability.
    """
    spark, path = parts.sparkSession, new_path(parts.sparkSession, "backoff")
    least = F.lit(2.0**-50)  # what is left is over 0; sums of doubles could round it away
    sums = parts.groupBy("order", "key").agg(F.sum("kept").alias("kept"), F.sum("lower").alias("lower"))
    sums.select("order", "key", F.log10(F.greatest(1 - F.col("kept"), least) / F.greatest(1 - F.col("lower"), least)).alias("value")).write.partitionBy("order").parquet(path)
    return spark.read.schema("key long, value double, order int").parquet(path)


def ngram_table(docs: DataFrame, order: int = 2, folds: int = 10, held: int = 0, least_count: int = 2, block_bytes: int = 3 << 20, part_bytes: int = 5 << 20, fan: int = 4096) -> DataFrame:
    """The kept n-gram counts as a table stored by order: key (64-bit hash), n, ngram (its words)."""
    packed_docs = blocks(docs, block_bytes)
    exchange = Exchange.over(packed_docs, part_bytes, fan)

    def first(rows):
        for batch in rows:
            for block in block_rows(batch):
                g = BlockGrams(block, order, folds, held)
                yield asked(block, g.distinct, [g.count, g.kind], exchange)

    def owned(block: Block, got: dict) -> pa.Table:
        g = BlockGrams(block, order, folds, held)
        count, owner = got[0]
        names = [x for t in block.texts for x in (*[b"<s>"] * max(order - 1, 1), *t.lower().split(), b"</s>")]
        mine = np.flatnonzero((owner > 0) & (g.kind > 0) & (count >= np.where(g.kind > 1, least_count, 1)))
        text = [b" ".join(names[g.first[i] - g.kind[i] + 1 : g.first[i] + 1]).decode() for i in mine]
        return pa.table({"key": pa.array(g.distinct[mine].view(np.int64)), "ngram": pa.array(text, pa.string()), "n": pa.array(count[mine].astype(np.int64)), "order": pa.array(g.kind[mine].astype(np.int32))})

    counted = written(answered(packed_docs.mapInArrow(first, ASK_SCHEMA), exchange, _answer(5, order)), "counts").withColumn("level", F.lit(0))
    spark, path = docs.sparkSession, new_path(docs.sparkSession, "ngrams")
    meet(packed_docs, counted, owned, "key long, ngram string, n long, order int").write.partitionBy("order").parquet(path)
    return spark.read.schema("key long, ngram string, n long, order int").parquet(path)
