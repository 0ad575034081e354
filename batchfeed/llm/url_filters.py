"""URL filters: rule lookup by Bloom filter cascades, without joins.

Rules list keys `host + path prefix`. A cascade holds two disjoint sets: level 0 is a
Bloom filter of the listed keys, level 1 one of the keys of the universe that level 0
lets through wrongly, level 2 of the listed keys that level 1 lets through, and so on
until a level makes no error. For every key of the universe (all candidate keys of the
corpus) the depth at which the levels stop a key tells exactly whether it is listed.

One cascade tells which keys are listed at all, small ones over the listed keys tell
their verdicts. A filter's bits are aggregated in Spark as 64-bit words and broadcast;
sets too large for `max_filter_bytes` are cut by key hash into shards, as many as the
counts ask for, and looked up one shard at a time.

Edge cases: a null url or one without `://` has empty host and path and fits no rule;
urls without a rule get the default verdict; repeated pages are judged one by one; an
empty table or no rules work alike; other columns of pages are not read.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, functions as F

from .common import written

#: Fixed values of the production rules: verdict, host, path prefix.
RULES = (
    ("allow", "com", "/"),
    ("block", "example.com", "/en/"),
    ("allow", "www.example.com", "/en/"),
    ("block", "net", "/es/"),
    ("block", "net", "/fr/"),
)


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Host: after the first `://` up to `/`, `?`, `#`, A-Z lowered; path: up to `?` or `#`."""
    at = F.coalesce(F.instr(url, "://"), F.lit(0))
    rest = F.when(at > 0, url.substr(at + 3, F.length(url))).otherwise(F.lit(""))
    host = F.regexp_extract(rest, r"(?s)^([^/?#]*)", 1)
    return F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), F.regexp_extract(rest, r"(?s)^[^/?#]*([^?#]*)", 1)


def candidate_keys(host: Column, path: Column, prefix_lengths: list[int]) -> Column:
    """All `suffix of host` + `prefix of path` keys that some rule of these lengths could list."""
    parts = F.split(host, r"\.")
    suffixes = F.transform(F.sequence(F.lit(1), F.size(parts)), lambda i: F.array_join(F.slice(parts, i, F.size(parts)), "."))
    prefixes = F.filter(F.array(*(F.when(F.length(path) >= n, path.substr(1, n)) for n in prefix_lengths)), lambda p: p.isNotNull())
    both = F.flatten(F.transform(suffixes, lambda s: F.transform(prefixes, lambda p: F.concat(s, p))))
    return F.when(host == "", F.array().cast("array<string>")).otherwise(both)


@dataclass
class Level:
    bits: np.ndarray
    n_bits: int
    hashes: int
    seed: int


def _positions(h1: np.ndarray, h2: np.ndarray, level: Level) -> np.ndarray:
    """Bit positions (keys x hashes) by double hashing, other at each level."""
    with np.errstate(over="ignore"):
        a = h1.view(np.uint64) + np.uint64(level.seed) * h2.view(np.uint64)
        a = a * np.uint64(0x9E3779B97F4A7C15)
        a ^= a >> np.uint64(31)
        b = (h2.view(np.uint64) * np.uint64(0xBF58476D1CE4E5B9)) | np.uint64(1)
        return (a[:, None] + np.arange(level.hashes, dtype=np.uint64) * b[:, None]) % np.uint64(level.n_bits)


def _holds(level: Level, h1: np.ndarray, h2: np.ndarray) -> np.ndarray:
    if not len(h1):
        return np.zeros(0, bool)
    at = _positions(h1, h2, level)
    return ((level.bits[(at >> np.uint64(6)).astype(np.int64)] >> (at & np.uint64(63))) & np.uint64(1)).all(axis=1)


class Cascade:
    """Exact membership for the keys of the universe it was built over."""

    def __init__(self, levels: list[Level]):
        self.levels = levels

    def listed(self, h1: np.ndarray, h2: np.ndarray) -> np.ndarray:
        """True where the first level that lacks the key is an odd one."""
        depth = np.zeros(len(h1), np.int64)
        going = np.arange(len(h1))
        for level in self.levels:
            going = going[_holds(level, h1[going], h2[going])]
            depth[going] += 1
        return depth % 2 == 1

    @property
    def n_bytes(self) -> int:
        return sum(x.bits.nbytes for x in self.levels)


def key_hashes(key: Column) -> tuple[Column, Column]:
    return F.xxhash64(key), F.xxhash64(key, F.lit("second"))


def _shape(n: int, rate: float, seed: int) -> Level:
    """A filter for n keys at this rate of errors, without its bits."""
    n_bits = max(64, -(-math.ceil(n * -math.log(rate) / math.log(2) ** 2) // 64) * 64)
    return Level(np.zeros(0, np.uint64), n_bits, min(20, max(1, round(n_bits / max(n, 1) * math.log(2)))), seed)


def _words(shape: Level, h1: np.ndarray, h2: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The words of the filter that these keys set, and their bits."""
    at = _positions(h1, h2, shape).ravel()
    words, where = np.unique(at >> np.uint64(6), return_inverse=True)
    bits = np.zeros(len(words), np.uint64)
    np.bitwise_or.at(bits, where, np.uint64(1) << (at & np.uint64(63)))
    return words.astype(np.int64), bits


def _filled(shape: Level, words: np.ndarray, bits: np.ndarray) -> Level:
    out = np.zeros(shape.n_bits // 64, np.uint64)
    out[words] = bits
    return Level(out, shape.n_bits, shape.hashes, shape.seed)


def _longs(batch: pa.RecordBatch | pa.Table, name: str) -> np.ndarray:
    return batch[name].to_numpy(zero_copy_only=False) if isinstance(batch, pa.RecordBatch) else batch[name].to_numpy()


def _arrays(keys: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """The keys on the driver; only for sets of a checked size."""
    found = keys.select("h1", "h2").toArrow()
    return _longs(found, "h1"), _longs(found, "h2")


def _filter_of(keys: DataFrame, shape: Level) -> Level:
    """A Bloom filter of keys(h1, h2): one job, whose words are OR-ed together by Spark."""

    def bits(rows):
        for batch in rows:
            words, found = _words(shape, _longs(batch, "h1"), _longs(batch, "h2"))
            yield pa.RecordBatch.from_arrays([pa.array(words), pa.array(found.view(np.int64))], ["word", "bits"])

    out = keys.select("h1", "h2").mapInArrow(bits, "word long, bits long").groupBy("word").agg(F.bit_or("bits").alias("bits")).toArrow()
    return _filled(shape, _longs(out, "word"), _longs(out, "bits").astype(np.int64).view(np.uint64))


def _passing(keys: DataFrame, level: Level) -> DataFrame:
    held = keys.sparkSession.sparkContext.broadcast(level)

    def run(rows):
        for batch in rows:
            yield batch.filter(pa.array(_holds(held.value, _longs(batch, "h1"), _longs(batch, "h2"))))

    return keys.mapInArrow(run, keys.schema)


def _local_levels(member: tuple, other: tuple, seed: int, max_levels: int) -> list[Level]:
    """The levels that remain, of sets that are on the driver."""
    out = []
    while len(member[0]):
        if len(out) == max_levels:
            raise ValueError("two different keys share both hashes")
        shape = _shape(len(member[0]), 0.5, seed + len(out))
        level = _filled(shape, *_words(shape, *member))
        out.append(level)
        wrong = _holds(level, *other)
        member, other = (other[0][wrong], other[1][wrong]), member
    return out


def build_cascade(listed: DataFrame, universe: DataFrame, first_rate: float = 0.01, local_keys: int = 100_000, max_levels: int = 64) -> Cascade:
    """Cascade of `listed` against `universe`, both frames of (h1, h2), repeats allowed.

    Keys of the universe that are listed belong to the listed side. The universe is read
    once, through level 0: only the keys that pass it wrongly are made distinct and
    stored, and each further level looks at what the one before let through. The levels
    shrink by half at least; the rest is built on the driver once its two sets have
    at most `local_keys` keys together, by the same functions.
    """
    inside = written(listed.select("h1", "h2").distinct(), "cascade")
    n = inside.count()
    if not n:
        return Cascade([])

    def level_of(keys: DataFrame, size: int, rate: float, seed: int) -> Level:
        shape = _shape(size, rate, seed)
        return _filled(shape, *_words(shape, *_arrays(keys))) if size <= local_keys else _filter_of(keys, shape)

    levels = [level_of(inside, n, first_rate, 1)]
    wrong = _passing(universe.select("h1", "h2"), levels[0]).distinct().join(inside, ["h1", "h2"], "left_anti")
    member, other = written(wrong, "cascade"), inside
    sizes = [n, member.count()]
    while sizes[-1]:
        if len(levels) == max_levels:
            raise ValueError("two different keys share both hashes")
        if sizes[-1] + sizes[-2] <= local_keys:
            return Cascade(levels + _local_levels(_arrays(member), _arrays(other), len(levels) + 1, max_levels - len(levels)))
        levels.append(level_of(member, sizes[-1], 0.5, len(levels) + 1))
        member, other = written(_passing(other, levels[-1]), "cascade"), member
        sizes.append(member.count())
    return Cascade(levels)


def _lookup(cascades, shard: int, shards: int):
    """A UDF that gives for arrays of key hashes the place of the key's verdict, -1 if it is not listed.

    cascades: broadcast, of all listed keys and of each verdict's among these.
    """

    @F.arrow_udf("array<int>")
    def verdicts(a: pa.Array, b: pa.Array) -> pa.Array:
        x, y = a.flatten().to_numpy(zero_copy_only=False), b.flatten().to_numpy(zero_copy_only=False)
        whole, each = cascades.value
        out = np.full(len(x), -1, np.int32)
        hit = np.flatnonzero(whole.listed(x, y) & (x % shards == shard))
        for k, one in enumerate(each):
            out[hit[one.listed(x[hit], y[hit])]] = k
        sizes = pc.fill_null(pc.list_value_length(a), 0).to_numpy(zero_copy_only=False)
        return pa.ListArray.from_arrays(pa.array(np.append(0, np.cumsum(sizes)).astype(np.int32)), pa.array(out))

    return verdicts


def judge(pages: DataFrame, rules: tuple = RULES, default: str = "allow", shards: int | None = None, max_filter_bytes: int = 64 << 20, local_keys: int = 100_000) -> DataFrame:
    """page_id, host, path, rule, verdict of every row of pages(page_id, url).

    rules: (verdict, host, path prefix); of the rules that fit, the longest `host + prefix`
    wins (equal lengths: the longer host, then the later verdict by name). Unlisted urls
    get the default. shards: parts of the key space, each with a cascade of its own that
    is looked up in turn; by default as many as keep every filter under max_filter_bytes.
    """
    spark = pages.sparkSession
    lengths = sorted({len(p) for _, _, p in rules}) or [0]
    kinds = sorted({v for v, _, _ in rules}) or [default]
    host, path = host_and_path(F.col("url"))
    split = pages.select("page_id", host.alias("host"), path.alias("path"))
    with_keys = split.withColumn("keys", candidate_keys(F.col("host"), F.col("path"), lengths))
    h1, h2 = key_hashes(F.col("key"))
    universe = with_keys.select(F.explode("keys").alias("key")).select(h1.alias("h1"), h2.alias("h2"))
    listed = written(spark.createDataFrame([(v, h + p) for v, h, p in rules], "verdict string, key string").select("verdict", h1.alias("h1"), h2.alias("h2")), "rules")
    n = len({h + p for _, h, p in rules})
    # errors of level 0 as many as listed keys, by an estimate of the universe: it sets sizes alone
    about = universe.agg(F.approx_count_distinct("h1")).first()[0]
    rate = min(0.5, max(n / (about + 1) / math.sqrt(2), 2.0**-30))
    shards = shards or max(1, -(-_shape(n, rate, 1).n_bits // 8 // max_filter_bytes))
    mine = lambda df, shard: df.where(F.pmod(F.col("h1"), F.lit(shards)) == shard) if shards > 1 else df
    out = with_keys.withColumn("marks", F.transform("keys", lambda k: F.lit(-1)))
    for shard in range(shards):
        known = mine(listed, shard)
        cascades = build_cascade(known, mine(universe, shard), rate, local_keys), [build_cascade(known.where(F.col("verdict") == v), known, 0.5, local_keys) for v in kinds]
        verdicts = _lookup(spark.sparkContext.broadcast(cascades), shard, shards)
        found = verdicts(F.transform("keys", lambda k: F.xxhash64(k)), F.transform("keys", lambda k: F.xxhash64(k, F.lit("second"))))
        out = out.withColumn("marks", F.zip_with("marks", found, lambda a, b: F.greatest(a, b)) if shard else found)
    both = F.filter(F.arrays_zip(F.col("keys").alias("k"), F.col("marks").alias("m")), lambda z: z["m"] >= 0)
    best = F.array_max(F.transform(both, lambda z: F.struct(F.length(z["k"]).alias("n"), F.instr(z["k"], "/").alias("h"), z["k"].alias("key"), F.element_at(F.array(*map(F.lit, kinds)), z["m"] + 1).alias("verdict"))))
    return out.select("page_id", "host", "path", best["key"].alias("rule"), F.coalesce(best["verdict"], F.lit(default)).alias("verdict"))
