"""Mixing sources to target weights by balanced sampling with the cube method.

Each document of a source has the same expected number of copies, target / source
size: its whole part is taken for sure, its fraction is the inclusion probability of
one copy more. The flight moves the probabilities of a few documents at a time along
vectors that leave the balancing totals (documents and words) unchanged, until each is
0 or 1 but for as many as there are constraints.

Groups of (source, bucket) of bounded size fly apart. A group keeps a reserve, spread
evenly over its sizes, out of its flight; reserves and what is left open are grouped
anew, level by level, until a source is one group. There the largest open documents
are decided first, each against all smaller ones at once, so that the last few are the
smallest: the landing problem, solved by looking at every choice of them for the one
nearest the source's own target; what is still missing is made up by turning choices
of other documents.

Edge cases: null or empty texts have size 0 and take 0 words; a source without words
has target 0; a null source is a source of its own; repeated rows are units of their
own; no row gives an empty result; other columns of docs may have any name.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window as W, functions as F

from .common import free_name, written

#: Weights of the sources in code point order, repeating.
WEIGHTS = (5, 2, 1)
LIMIT = 3.0


def words_of(text: Column) -> Column:
    """Number of `[^\\x20\\x09-\\x0D]+` words, 0 for null."""
    return F.coalesce(F.regexp_count(text, F.lit("[^\\x20\\x09-\\x0D]+")), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights: tuple = WEIGHTS, limit: float = LIMIT) -> DataFrame:
    """source, n, source_size, target: weighted shares of all sizes, water-filled below limit * size.

    One row per source, so the windows over all sources see few rows. Sources by
    limit / weight: a prefix is capped, the rest share what is left.
    """
    by = sizes.groupBy("source").agg(F.count("*").alias("n"), F.sum("size").cast("long").alias("source_size"))
    order = W.orderBy(F.col("source").cast("binary").asc_nulls_last())
    k = F.pmod(F.row_number().over(order) - 1, F.lit(len(weights)))
    by = by.withColumn("weight", F.element_at(F.array(*(F.lit(float(w)) for w in weights)), (k + 1).cast("int")))
    by = by.withColumn("cap", limit * F.col("source_size")).withColumn("level", F.col("cap") / F.col("weight"))
    whole = W.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    before = W.orderBy("level", F.col("source").asc_nulls_last()).rowsBetween(W.unboundedPreceding, -1)
    by = by.withColumn("all_size", F.sum("source_size").over(whole)).withColumn("all_weight", F.sum("weight").over(whole))
    by = by.withColumn("rise", (F.col("all_size") - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / (F.col("all_weight") - F.coalesce(F.sum("weight").over(before), F.lit(0.0))))
    by = by.withColumn("water", F.max(F.when(F.col("rise") <= F.col("level"), F.col("rise"))).over(whole))
    return by.select("source", "n", "source_size", F.least("cap", F.coalesce(F.col("water") * F.col("weight"), F.col("cap"))).alias("target"))


def fly(probability: np.ndarray, measures: np.ndarray, noise: np.ndarray) -> np.ndarray:
    """Flight phase: all but at most measures.shape[1] probabilities end at 0 or 1.

    measures: value of each unit in each balanced total. noise: a uniform number per
    unit, spent one a step.
    """
    p = probability.astype(float).copy()
    k = measures.shape[1]
    waiting = [i for i in range(len(p)) if 1e-9 < p[i] < 1 - 1e-9]
    waiting.reverse()
    held: list[int] = []
    steps = 0
    while True:
        while len(held) <= k and waiting:
            held.append(waiting.pop())
        if len(held) <= k:
            break
        a = measures[held].T
        if k == 2:
            u = np.cross(a[0], a[1])
            if not u.any():
                u = np.array([-a[0, 1], a[0, 0], 0.0]) if a[0, :2].any() else np.array([1.0, 0.0, 0.0]) if not a[:, 0].any() else np.linalg.svd(a)[2][-1]
        else:
            u = np.linalg.svd(a)[2][-1]
        u = [float(v) for v in u / max(abs(u).max(), 1e-300)]
        up = min((1 - p[i]) / v if v > 0 else p[i] / -v for i, v in zip(held, u, strict=True) if abs(v) > 1e-12)
        down = min(p[i] / v if v > 0 else (1 - p[i]) / -v for i, v in zip(held, u, strict=True) if abs(v) > 1e-12)
        move = up if noise[steps % len(noise)] < down / (up + down) else -down
        steps += 1
        for i, v in zip(held, u, strict=True):
            p[i] = min(1.0, max(0.0, p[i] + move * v))
        held = [i for i in held if 1e-9 < p[i] < 1 - 1e-9]
    return np.where(p < 1e-9, 0.0, np.where(p > 1 - 1e-9, 1.0, p))


def decide_large(probability: np.ndarray, measures: np.ndarray, noise: np.ndarray, last: int = 12) -> np.ndarray:
    """Go on from a flight until `last` probabilities are open, the largest units first.

    measures: rows (1, size). The largest open unit moves against all other open ones,
    each by its room p(1 - p), so that documents and words stay as they are; where that
    would not settle it, words alone are kept.
    """
    p, size = probability.astype(float).copy(), measures[:, 1]
    open_ = np.flatnonzero((p > 1e-9) & (p < 1 - 1e-9))
    open_ = open_[np.argsort(-size[open_], kind="stable")]
    steps = 0
    while len(open_) > last:
        top, rest = open_[0], open_[1:]
        room, s = p[rest] * (1 - p[rest]), size[rest]
        g0, g1, g2 = room.sum(), (room * s).sum(), (room * s * s).sum()
        tries = []
        det = g0 * g2 - g1 * g1
        if det > 1e-9 * max(g0 * g2, 1e-300):
            tries.append(room * ((g1 * size[top] - g2) + (g1 - g0 * size[top]) * s) / det)
        tries.append(-size[top] / g1 * room if g1 > 0 else -room / g0)
        for v in tries:
            u, here = np.append(1.0, v), p[open_]
            with np.errstate(divide="ignore"):
                up = np.where(u > 1e-15, (1 - here) / u, np.where(u < -1e-15, here / -u, np.inf))
                down = np.where(u > 1e-15, here / u, np.where(u < -1e-15, (1 - here) / -u, np.inf))
            if up.argmin() == 0 and down.argmin() == 0:
                break
        move = up.min() if noise[steps % len(noise)] < down.min() / (up.min() + down.min()) else -down.min()
        steps += 1
        p[open_] = np.clip(here + move * u, 0, 1)
        p[open_] = np.where(p[open_] < 1e-9, 0.0, np.where(p[open_] > 1 - 1e-9, 1.0, p[open_]))
        open_ = open_[(p[open_] > 0) & (p[open_] < 1)]
    return p


def land(probability: np.ndarray, size: np.ndarray, words: float) -> np.ndarray:
    """Round the few open units: of all choices, the one whose words are nearest to those expected.

    words: what the whole source should take of these units. Ties go to the number of units nearest to that expected.
    """
    p = probability.copy()
    open_ = np.flatnonzero((p > 0) & (p < 1))
    k = len(open_)
    choice = (np.arange(1 << k)[:, None] >> np.arange(k)) & 1
    off = np.abs((p == 1) @ size + choice @ size[open_] - words)
    count = np.abs(choice.sum(1) - p[open_].sum())
    p[open_] = choice[np.lexsort((count, np.round(off, 6)))[0]] if k else p[open_]
    return p


def settle(p: np.ndarray, size: np.ndarray, words: float) -> np.ndarray:
    """Turn single choices while that brings the words taken nearer to those expected.

    Only needed where a large unit was open last; each turn is of the unit that fits best.
    """
    p = p.copy()
    off = p @ size - words
    while True:
        turn = (p == (off > 0)) & (size > 0) & (size < 2 * abs(off) - 1e-6)
        if not turn.any():
            return p
        at = np.where(turn, np.abs(abs(off) - size), np.inf).argmin()
        off += size[at] if p[at] == 0 else -size[at]
        p[at] = 1 - p[at]


def _noise(seed: Column) -> Column:
    return F.pmod(F.xxhash64(seed, F.lit("cube")), F.lit(1 << 30)) / F.lit(float(1 << 30))


def _flight(units: DataFrame, reserve: int) -> DataFrame:
    """Fly within each group of a source; groups that are the whole source land.

    units(uid, copy, p, size, source, group, groups, order, noise).
    """
    schema = units.schema

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["size", "order", "uid", "copy"], ascending=[False, True, True, True], kind="stable").reset_index(drop=True)
        p, size, noise = pdf.p.to_numpy(float).copy(), pdf["size"].to_numpy(float), pdf.noise.to_numpy()
        words = float(p @ size)
        measures = np.stack([np.ones(len(pdf)), size], axis=1)
        kept = np.unique(np.linspace(0, len(pdf) - 1, min(reserve, len(pdf))).astype(int))
        goes = np.setdiff1d(np.arange(len(pdf)), kept)
        if len(goes):
            p[goes] = fly(p[goes], measures[goes], noise[goes])
        if pdf.groups.iloc[0] <= 1:
            p = settle(land(decide_large(p, measures, noise), size, words), size, words)
        pdf["p"] = p
        return pdf

    return units.groupBy("source", "group").applyInPandas(run, schema)


def mix(docs: DataFrame, weights: tuple = WEIGHTS, limit: float = LIMIT, bucket_docs: int = 4_000, reserve: int = 128, keep_columns: bool = False) -> DataFrame:
    """doc_id, source, size, source_size, target, copies of every row of docs.

    keep_columns: instead the rows of docs, each as often as it is taken.
    """
    sizes = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "source", words_of(F.col("text")).alias("size"))
    sizes = written(sizes, "sizes")
    targets = written(source_targets(sizes, weights, limit), "targets")
    # equal rows of a repeated doc_id are numbered, so that each is a unit
    units = sizes.groupBy(F.coalesce("doc_id", F.lit(-(1 << 62))).alias("uid"), "source", "size").agg(F.count("*").alias("times"), F.first("doc_id").alias("doc_id"))
    units = units.select("*", F.explode(F.sequence(F.lit(1), F.col("times").cast("int"))).alias("copy")).drop("times")
    per = targets.select(F.col("source").alias("_s"), "n", "source_size", "target", F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0).alias("expected"))
    units = units.join(per, F.col("source").eqNullSafe(F.col("_s"))).drop("_s")
    base = F.floor(F.col("expected") + 1e-9)
    seed = F.concat_ws(":", "uid", "copy", "size", "source")
    units = units.withColumn("base", base.cast("int")).withColumn("p", F.greatest(F.lit(0.0), F.col("expected") - base)).withColumn("order", F.xxhash64(seed)).withColumn("noise", _noise(seed))
    # n: how many units of the source there may be at this level
    level, done, most = 0, None, int(targets.agg(F.max("n")).first()[0] or 0)
    while True:
        units = units.withColumn("groups", F.greatest(F.lit(1), F.ceil(F.col("n") / bucket_docs)).cast("long"))
        units = units.withColumn("group", F.pmod(F.xxhash64(seed, F.lit(f"level {level}")), F.col("groups")))
        flown = written(_flight(units, reserve), "flight")
        settled = flown.where("groups <= 1 OR p <= 0 OR p >= 1")
        done = settled if done is None else done.unionByName(settled)
        if most <= bucket_docs:
            break
        # a group leaves its reserve and one open unit a constraint
        most = -(-most // bucket_docs) * (reserve + 2)
        units = flown.where("groups > 1 AND p > 0 AND p < 1").withColumn("n", F.col("groups") * (reserve + 2))
        level += 1
    done = done.select("doc_id", "source", "size", "source_size", "target", (F.col("base") + F.round("p")).cast("int").alias("copies"))
    if not keep_columns:
        return done
    name = {c: free_name(docs, c) for c in ("d", "s", "n", "c", "k", "size", "copies", "i")}
    taken = done.groupBy(F.col("doc_id").alias(name["d"]), F.col("source").alias(name["s"]), F.col("size").alias(name["n"])).agg(F.array_sort(F.collect_list("copies")).alias(name["c"]), F.count("*").alias(name["k"]))
    taken = taken.where(F.array_max(name["c"]) > 0).hint("shuffle_hash")  # the narrow side is hashed, the texts aren't sorted
    cols = [F.col(f"`{c}`") for c in docs.columns]
    same = F.col("doc_id").cast("long").eqNullSafe(F.col(name["d"])) & F.col("source").eqNullSafe(F.col(name["s"])) & (F.col(name["size"]) == F.col(name["n"]))
    joined = docs.withColumn(name["size"], words_of(F.col("text"))).join(taken, same)
    single = joined.where(F.col(name["k"]) == 1).select(*cols, F.element_at(name["c"], 1).alias(name["copies"]))
    # rows of one repeated unit share its copies: the first by text has the fewest
    number = F.row_number().over(W.partitionBy(name["d"], name["s"], name["n"]).orderBy("text"))
    repeated = joined.where(F.col(name["k"]) > 1).select(*cols, F.element_at(name["c"], number.cast("int")).alias(name["copies"]))
    both = single.unionByName(repeated) if not done.groupBy("doc_id", "source", "size").count().where("count > 1").isEmpty() else single
    return both.where(F.col(name["copies"]) > 0).select(*cols, F.explode(F.sequence(F.lit(1), F.col(name["copies"]))).alias(name["i"])).drop(name["i"])


def digest(mixed: DataFrame) -> DataFrame:
    return mixed.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).cast("long").alias("taken"))
