"""Quality classifier: histogram gradient-boosted trees over document statistics.

Statistics of every whole text are computed once, in one pass, and kept as a narrow
table; the fit sees at most `max_fit_docs` labelled rows of it. Trees grow level by
level on binned features with Newton gains, and are flattened into arrays that numpy
walks for all rows of a batch at once.

Edge cases: null and empty texts have zero statistics and get a score like others;
labels that are null or of a held-out or missing document teach nothing; without any
label, or labels of one kind, all scores are the labels' share (0.5 if there is none);
of several labels of one document the largest counts; rows of one doc_id are scored each.
"""

from __future__ import annotations

import math
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .common import batches, texts, written

FEATURES = ("log_bytes", "log_words", "word_bytes", "distinct_share", "adjacent_repeats", "top_word", "pair_repeats", "log_lines", "line_words", "duplicate_lines", "blank_lines", "short_lines", "capitals", "digits", "spaces", "punctuation", "hash_signs", "pipes", "bangs", "wide_symbols", "non_ascii", "sentence_ends", "capital_words", "longest_word", "at_signs", "slashes", "underscores", "compression")
_CAPITALS, _DIGITS, _SPACES = bytes(range(65, 91)), bytes(range(48, 58)), b" \t\r\x0b\x0c"


def statistics(text: bytes) -> tuple[float, ...]:
    """The features of one text."""
    n = max(len(text), 1)
    words = text.split()
    k = max(len(words), 1)
    lines = text.split(b"\n")
    counts = Counter(words)
    full = [x for x in lines if x and not x.isspace()]
    share = lambda drop: (len(text) - len(text.translate(None, drop))) / n
    pairs = len(set(zip(words, words[1:])))
    return (
        math.log1p(len(text)),
        math.log1p(len(words)),
        sum(map(len, words)) / k,
        len(counts) / k,
        sum(map(bytes.__eq__, words, words[1:])) / k,
        max(counts.values(), default=0) / k,
        1 - pairs / max(len(words) - 1, 1),
        math.log1p(len(full)),
        len(words) / max(len(full), 1),
        1 - len(set(full)) / max(len(full), 1),
        1 - len(full) / max(len(lines), 1),
        sum(len(x) < 40 for x in full) / max(len(full), 1),
        share(_CAPITALS),
        share(_DIGITS),
        share(_SPACES),
        share(b".,;:?!"),
        share(b"#*$%&"),
        share(b"|"),
        text.count(b"!") / n,
        share(b"<>{}[]()=+"),
        sum(map(text.count, (b"\xc3", b"\xc5", b"\xe2", b"\xf0"))) / n,
        text.count(b". ") / k,
        (len(words) - sum(map(bytes.islower, words))) / k,
        max(map(len, counts), default=0),
        text.count(b"@") / k,
        text.count(b"/") / k,
        text.count(b"_") / k,
        sum(map(len, counts)) / n,
    )


def document_statistics(docs: DataFrame) -> DataFrame:
    """doc_id and `x`, the features as float32 bytes, of every row."""

    def run(rows):
        for batch in batches(rows, 8 << 20):
            x = [np.array(statistics(t), "<f4").tobytes() for t in texts(batch["text"])]
            yield pa.RecordBatch.from_arrays([batch["doc_id"], pa.array(x, pa.binary())], ["doc_id", "x"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, x binary")


def matrix(x: pa.Array | list[bytes]) -> np.ndarray:
    return np.frombuffer(b"".join(x if isinstance(x, list) else x.to_pylist()), "<f4").reshape(-1, len(FEATURES))


@dataclass
class BoostedTrees:
    """Trees as arrays over all nodes: feature (-1 at leaves), threshold, left child, value."""

    prior: float
    roots: np.ndarray
    feature: np.ndarray
    threshold: np.ndarray
    left: np.ndarray
    value: np.ndarray
    depth: int

    def scores(self, x: np.ndarray) -> np.ndarray:
        """Probability of label 1 for each row of x."""
        total = np.full(len(x), self.prior)
        rows = np.arange(len(x))
        for root in self.roots:
            at = np.full(len(x), root)
            for _ in range(self.depth):
                f = self.feature[at]
                inner = f >= 0
                right = x[rows, np.maximum(f, 0)] > self.threshold[at]
                at = np.where(inner, self.left[at] + right, at)
            total += self.value[at]
        return 1 / (1 + np.exp(-total))


def fit(x: np.ndarray, y: np.ndarray, trees: int = 80, depth: int = 5, bins: int = 64, rate: float = 0.15, ridge: float = 1.0, least_rows: int = 20) -> BoostedTrees:
    """Boost trees on logistic loss."""
    p = (y.sum() + 0.5) / (len(y) + 1.0) if len(y) else 0.5
    prior = math.log(p / (1 - p))
    empty = BoostedTrees(prior, np.zeros(0, int), np.array([-1]), np.zeros(1, np.float32), np.zeros(1, int), np.zeros(1), depth)
    if not len(y) or y.min() == y.max():
        return empty
    x = np.ascontiguousarray(x, np.float32)
    edges = [np.unique(np.quantile(c, np.linspace(0, 1, bins + 1)[1:-1], method="lower")) for c in x.T]
    binned = np.stack([np.searchsorted(e, c, side="left") for e, c in zip(edges, x.T, strict=True)], axis=1)
    width = x.shape[1]
    flat = binned + np.arange(width) * bins
    feature, threshold, left, value, roots = [], [], [], [], []
    score = np.full(len(y), prior)
    for _ in range(trees):
        q = 1 / (1 + np.exp(-score))
        g, h = y - q, q * (1 - q)
        root = len(feature)
        roots.append(root)
        feature.append(-1), threshold.append(0.0), left.append(0), value.append(0.0)
        node, level = np.full(len(y), root), [root]
        for d in range(depth + 1):
            order = {k: i for i, k in enumerate(level)}
            local = np.array([order.get(k, -1) for k in range(root, len(feature))])[node - root]
            on = local >= 0
            sums = [np.bincount(local[on], w[on], len(level)) for w in (g, h, np.ones(len(y)))]
            for i, k in enumerate(level):
                value[k] = rate * sums[0][i] / (sums[1][i] + ridge)
            if d == depth:
                break
            size = width * bins
            key = (local[on, None] * size + flat[on]).ravel()
            hist = [np.bincount(key, np.repeat(w[on], width), len(level) * size).reshape(len(level), width, bins).cumsum(2) for w in (g, h, np.ones(len(y)))]
            rest = [s[:, None, None] - c for s, c in zip(sums, hist, strict=True)]
            gain = hist[0] ** 2 / (hist[1] + ridge) + rest[0] ** 2 / (rest[1] + ridge) - (sums[0] ** 2 / (sums[1] + ridge))[:, None, None]
            gain[(hist[2] < least_rows) | (rest[2] < least_rows)] = -1
            best = gain.reshape(len(level), -1).argmax(1)
            grown = []
            for i, k in enumerate(level):
                f, b = divmod(int(best[i]), bins)
                if gain[i, f, b] <= 1e-6 or b >= len(edges[f]):
                    continue
                feature[k], threshold[k], left[k] = f, float(edges[f][b]), len(feature)
                for _side in (0, 1):
                    grown.append(len(feature))
                    feature.append(-1), threshold.append(0.0), left.append(0), value.append(0.0)
                mine = node == k
                node[mine] = left[k] + (binned[mine, f] > b)
            level = grown
            if not level:
                break
        score += np.array(value)[node]
    return BoostedTrees(prior, np.array(roots), np.array(feature), np.array(threshold, np.float32), np.array(left), np.array(value), depth)


def bucket(doc_id, n: int):
    """crc32(doc_id as text) mod n as a column."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % n


def train(stats: DataFrame, labels: DataFrame, held_out: int = 1, folds: int = 3, max_fit_docs: int = 20_000, **options) -> BoostedTrees:
    """Fit on labelled rows whose bucket is not held_out, at most max_fit_docs of them.

    Rows with the least crc32 of a salted doc_id are taken, in that order, so the same ones each time.
    """
    known = labels.select("doc_id", F.col("quality").alias("y")).where("doc_id IS NOT NULL AND y IN (0, 1)").where(bucket(F.col("doc_id"), folds) != held_out).groupBy("doc_id").agg(F.max("y").alias("y"))
    rank = F.crc32(F.concat(F.lit("fit:"), F.col("doc_id").cast("string")).cast("binary"))
    chosen = known.orderBy(rank, "doc_id").limit(max_fit_docs)
    rows = stats.join(F.broadcast(chosen), "doc_id").select("doc_id", "x", "y", rank.alias("rank")).orderBy("rank", "doc_id", "x").limit(max_fit_docs).collect()
    return fit(matrix([bytes(r.x) for r in rows]), np.array([r.y for r in rows], float), **options)


def score(stats: DataFrame, model: BoostedTrees, held_out: int = 1, folds: int = 3) -> DataFrame:
    """doc_id, held_out, score and predicted of every row of stats."""
    held = stats.sparkSession.sparkContext.broadcast(model)

    def run(rows):
        for batch in rows:
            s = held.value.scores(matrix(batch["x"]))
            yield pa.RecordBatch.from_arrays([batch["doc_id"], pa.array(s, pa.float64()), pa.array((s >= 0.5).astype("i4"), pa.int32())], ["doc_id", "score", "predicted"])

    out = stats.mapInArrow(run, "doc_id long, score double, predicted int")
    return out.select("doc_id", (bucket(F.col("doc_id"), folds) == held_out).alias("held_out"), "score", "predicted")


def classify(docs: DataFrame, labels: DataFrame, held_out: int = 1, folds: int = 3, **options) -> DataFrame:
    """Statistics, fit and scores of docs(doc_id, text) in one call."""
    stats = written(document_statistics(docs), "statistics")
    return score(stats, train(stats, labels, held_out, folds, **options), held_out, folds)
