"""Benchmark decontamination by Wu-Manber multi-pattern search over words.

Patterns are the word windows of the benchmark items. For patterns of one length m a
table over blocks of two words gives how far the search may move on; blocks that end a
pattern point to the bucket of patterns with that suffix, split by the hash of the
first word, and direct comparison confirms. Items shorter than a window are single
patterns and have tables of their own for each length (at most `window` tables).

The benchmark is cut by item into blocks of about `max_pattern_bytes` of text, one of
which is broadcast and searched at a time (its tables take some hundred bytes a word).

Edge cases: null texts have no words; an item without words fits nothing; one of a null
item_id is searched too, its hits count but it is in no id list; overlapping
occurrences count a word once; repeated items are reported once each id; documents of
a repeated doc_id are judged row by row.
"""

from __future__ import annotations

from collections import defaultdict

import pyarrow as pa
from pyspark.sql import DataFrame, functions as F
from pyspark.sql.types import StructField, StructType

from .common import batches, free_name, texts, written

_WORD_BYTES = bytes(x if x >= 128 or chr(x).isalnum() else 32 for x in range(256)).lower()


def plain_words(text: bytes) -> list[bytes]:
    """Lower-cased words of letters, digits and non-ASCII bytes."""
    return text.translate(_WORD_BYTES).split()


class PatternTable:
    """Wu-Manber tables of patterns that all have the same number of words."""

    def __init__(self, patterns: dict[tuple, list[int]]):
        self.m = m = len(next(iter(patterns)))
        self.b = b = min(2, m)
        self.far = m - b + 1
        self.shift: dict = {}
        self.buckets: dict = defaultdict(list)
        for p, items in patterns.items():
            for end in range(b, m + 1):
                block = p[end - b : end] if b > 1 else p[end - 1]
                self.shift[block] = min(self.shift.get(block, self.far), m - end)
            self.buckets[p[-b:] if b > 1 else p[-1], p[0]].append((list(p), items))
        self.buckets = dict(self.buckets)

    def find(self, words: list[bytes], spans: list[tuple[int, int]], items: set) -> None:
        """Add the spans of all occurrences, in order, and the ids of their items."""
        m, far, b, n = self.m, self.far, self.b, len(words)
        shift, buckets = self.shift.get, self.buckets.get
        i = m
        while i <= n:
            block = (words[i - 2], words[i - 1]) if b > 1 else words[i - 1]
            step = shift(block, far)
            if step:
                i += step
                continue
            for p, ids in buckets((block, words[i - m]), ()):
                if words[i - m : i] == p:
                    spans.append((i - m, i))
                    items.update(ids)
            i += 1


def pattern_tables(items: list[tuple[int, bytes]], window: int) -> list[PatternTable]:
    """A table for each length; items are (number, text)."""
    by_length: dict[int, dict[tuple, list[int]]] = defaultdict(lambda: defaultdict(list))
    for number, text in items:
        words = plain_words(text)
        size = min(window, len(words))
        for i in range(len(words) - size + 1) if size else ():
            ids = by_length[size][tuple(words[i : i + size])]
            if not ids or ids[-1] != number:
                ids.append(number)
    return [PatternTable(p) for _, p in sorted(by_length.items())]


def covered(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """The union of spans as disjoint ones."""
    out: list[tuple[int, int]] = []
    for a, z in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(z, out[-1][1]))
        else:
            out.append((a, z))
    return out


ADDED = {"n_words": "long", "n_hit": "long", "spans": "array<struct<first:long,end:long>>", "item_ids": "array<string>", "contaminated": "boolean"}
_SPAN = pa.list_(pa.struct([("first", pa.int64()), ("end", pa.int64())]))
_RESULT = pa.struct([("n_words", pa.int64()), ("n_hit", pa.int64()), ("spans", _SPAN), ("item_ids", pa.list_(pa.string())), ("contaminated", pa.bool_())])


def _with_result(docs: DataFrame, into: str) -> StructType:
    return StructType([*docs.schema, StructField(into, StructType.fromDDL(", ".join(f"{k} {v}" for k, v in ADDED.items())))])


def _judged(n_words: int, spans: list[tuple[int, int]], ids: list[str], share: int) -> dict:
    hit = sum(z - a for a, z in spans)
    return {"n_words": n_words, "n_hit": hit, "spans": [{"first": a, "end": z} for a, z in spans], "item_ids": ids, "contaminated": hit > 0 and share * hit >= n_words}


def _find(text: bytes, tables: list[PatternTable], names: list[str | None]) -> tuple[int, list[tuple[int, int]], list[str]]:
    words = plain_words(text)
    spans, items = [], set()
    for t in tables:
        t.find(words, spans, items)
    return len(words), covered(spans), sorted({names[i] for i in items if names[i] is not None})


def _scan(docs: DataFrame, items: list[tuple[str | None, bytes]], window: int, share: int, into: str) -> DataFrame:
    """docs with a struct of what its `text` has of the items, in one pass."""
    held = docs.sparkSession.sparkContext.broadcast(items)
    schema = _with_result(docs, into)

    def run(rows):
        names = [x for x, _ in held.value]
        tables = pattern_tables([(i, t) for i, (_, t) in enumerate(held.value)], window)
        for batch in batches(rows, 8 << 20):
            found = pa.array([_judged(*_find(t, tables, names), share) for t in texts(batch["text"])], _RESULT)
            yield pa.RecordBatch.from_arrays([*batch.columns, found], [*batch.schema.names, into])

    return docs.mapInArrow(run, schema)


def found_in(docs: DataFrame, benchmark: DataFrame, into: str, window: int = 13, max_pattern_bytes: int = 2 << 20, share: int = 20) -> DataFrame:
    """docs with a struct column `into` of ADDED's fields.

    The benchmark is dealt by hash into as many blocks as keep each near max_pattern_bytes
    of text; the driver holds one block at a time. With one block, one pass does all. With
    several, each is searched over (doc_id, text) and leaves only the documents that it
    hits, under two hashes of the text; their union by document is joined back.
    """
    spark = docs.sparkSession
    items = benchmark.select(F.col("item_id").cast("string").alias("id"), F.coalesce("text", F.lit("")).alias("text")).distinct()
    size = items.agg(F.sum(F.octet_length("text").cast("long"))).first()[0] or 0
    blocks = max(1, -(-size // max_pattern_bytes))
    block_of = F.pmod(F.xxhash64("id", "text"), F.lit(blocks))

    def block(k: int) -> list[tuple[str | None, bytes]]:
        mine = items if blocks == 1 else items.where(block_of == k)
        return [(r.id, r.text.encode()) for r in mine.orderBy("id", "text").collect()]  # about max_pattern_bytes

    if blocks == 1:
        return _scan(docs, block(0), window, share, into)
    low, high = F.xxhash64("text"), F.xxhash64("text", F.lit("second"))
    texts_of = docs.select(F.col("doc_id").cast("string").alias("doc"), "text")
    hits = None
    for k in range(blocks):
        one = _scan(texts_of, block(k), window, share, "hit").where("hit.n_hit > 0").select("doc", low.alias("low"), high.alias("high"), "hit.spans", "hit.item_ids")
        one = written(one, "hits")
        hits = hits.unionByName(one) if hits else one
    ends = hits.groupBy("doc", "low", "high").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("spans")))).alias("spans"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("item_ids")))).alias("ids"))
    name = {c: free_name(docs, f"_{c}") for c in ends.columns}
    ends = ends.select(*(F.col(c).alias(n) for c, n in name.items()))
    same = F.col("doc_id").cast("string").eqNullSafe(F.col(name["doc"])) & (low == F.col(name["low"])) & (high == F.col(name["high"]))
    schema, own = _with_result(docs, into), docs.columns

    def count(rows):
        for batch in batches(rows, 8 << 20):
            found = []
            for text, spans, ids in zip(texts(batch["text"]), batch[name["spans"]].to_pylist(), batch[name["ids"]].to_pylist(), strict=True):
                found.append(_judged(len(plain_words(text)), covered([(x["first"], x["end"]) for x in spans or []]), ids or [], share))
            yield pa.RecordBatch.from_arrays([*(batch[c] for c in own), pa.array(found, _RESULT)], [*own, into])

    return docs.join(ends, same, "left").select(*(f"`{c}`" for c in own), name["spans"], name["ids"]).mapInArrow(count, schema)


def search(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """Per row of docs: doc_id, n_words, n_hit, spans (word ranges), item_ids, contaminated.

    contaminated: some word is hit and share * n_hit >= n_words.
    """
    return found_in(docs.select("doc_id", "text"), benchmark, "found", **options).select("doc_id", "found.*")


def digest(found: DataFrame) -> DataFrame:
    """The item list as its length and the SHA-256 of the comma-joined ids."""
    return found.select("doc_id", "n_words", "n_hit", F.size("item_ids").cast("long").alias("n_items"), F.sha2(F.array_join("item_ids", ","), 256).alias("items_sha256"), "contaminated")


def keep_clean(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """The rows of docs that are not contaminated, with their own columns, whatever their names."""
    into = free_name(docs, "found")
    return found_in(docs, benchmark, into, **options).where(f"NOT `{into}`.contaminated").select(*(f"`{c}`" for c in docs.columns))
