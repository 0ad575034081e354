"""Quality rules: text counts, and line labelling by a linear-chain CRF.

Every line with a word gets features; Viterbi decoding marks it content or
boilerplate, and the share of a document's words in content lines decides whether
it stays. The CRF is fitted on a bounded sample of the lines of labelled documents
(`max_fit_docs`, `max_fit_segments`); a line counts as boilerplate there if its document is labelled low quality, if it
repeats an earlier line, or if symbols fill over `WEAK_SYMBOL_SHARE` of it.

Edge cases: null and empty texts have no words, are base failures and are not kept;
rows of a repeated doc_id are judged one by one; without usable labels the fixed
starting weights decide; of several labels of one document the least counts.
"""

from __future__ import annotations

import zlib
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F
from pyspark.sql.types import StructField, StructType

from .common import ASCII_SPACE, batches, free_name, texts

SYMBOLS = "#*$%&|<>"
WEAK_SYMBOL_SHARE = 0.08
FEATURES = ("bias", "log_words", "word_length", "symbols", "capitals", "digits", "duplicate", "distinct_words", "sentence_end", "exclamations")
_NO_SYMBOLS, _NO_CAPITALS, _NO_DIGITS = SYMBOLS.encode(), bytes(range(65, 91)), bytes(range(48, 58))


@dataclass
class LineCRF:
    """Two states, 0 content and 1 boilerplate: unary scores of state 1, transitions, start."""

    weights: np.ndarray = field(default_factory=lambda: np.array([-1.5, 0, 0, 20.0, 3.0, 0, 1.5, -0.5, 0, 8.0]))
    step: np.ndarray = field(default_factory=lambda: np.array([[0.5, -0.5], [-0.5, 0.5]]))
    start: np.ndarray = field(default_factory=lambda: np.zeros(2))

    def decode(self, x: np.ndarray) -> list[int]:
        """The best state sequence of lines with features x; ties go to content."""
        unary = (x @ self.weights).tolist()
        (s00, s01), (s10, s11) = self.step.tolist()
        a, b = self.start[0], self.start[1] + unary[0]
        back = []
        for u in unary[1:]:
            from_a, from_b = a >= b + s10 - s00, a + s01 >= b + s11
            back.append((0 if from_a else 1, 0 if from_b else 1))
            a, b = max(a + s00, b + s10), max(a + s01, b + s11) + u
        state = 0 if a >= b else 1
        path = [state]
        for pair in reversed(back):
            state = pair[state]
            path.append(state)
        return path[::-1]


def line_features(text: bytes) -> tuple[np.ndarray, list[int], int]:
    """Features and word counts of the lines with a word, and how many repeat an earlier one."""
    rows, counts, seen, dups = [], [], set(), 0
    for line in text.split(b"\n"):
        words = line.split()
        if not words:
            continue
        n, size = len(words), len(line)
        dup = line in seen
        dups += dup
        seen.add(line)
        counts.append(n)
        rows.append((1.0, n, size / n, (size - len(line.translate(None, _NO_SYMBOLS))) / size, (size - len(line.translate(None, _NO_CAPITALS))) / size, (size - len(line.translate(None, _NO_DIGITS))) / size, dup, len(set(words)) / n, words[-1][-1:] in b".!?", line.count(b"!") / size))
    x = np.array(rows, dtype=np.float64).reshape(-1, len(FEATURES))
    x[:, 1] = np.log1p(x[:, 1])
    x[:, 2] = np.minimum(x[:, 2], 40) / 10
    return x, counts, dups


def repeated_words(words: list[bytes], size: int = 3) -> int:
    """Words inside windows of `size` words that occur twice or more."""
    windows = list(zip(*(words[i:] for i in range(size))))
    if len(set(windows)) == len(windows):
        return 0
    often = {w for w, n in Counter(windows).items() if n > 1}
    total, free = 0, 0
    for i, w in enumerate(windows):
        if w in often:
            total += i + size - max(i, free)
            free = i + size
    return total


def text_counts(text: bytes) -> dict:
    """The base counts, the line features and the lines' word counts of one text."""
    words = text.split()
    chars = text.decode()
    x, counts, dups = line_features(text)
    return {
        "n_words": len(words),
        "word_chars": len(chars) - sum(map(chars.count, ASCII_SPACE)),
        "n_symbols": len(text) - len(text.translate(None, _NO_SYMBOLS)),
        "n_dup_lines": dups,
        "n_repeat_words": repeated_words(words),
        "lines": x,
        "line_words": counts,
    }


def fit(sequences: list[tuple[np.ndarray, np.ndarray]], rounds: int = 80, length: int = 48, rate: float = 0.15, ridge: float = 1e-3) -> LineCRF:
    """Maximum likelihood by Adam over sequences (features, states), cut at `length` lines."""
    parts = [(x[i : i + length], y[i : i + length]) for x, y in sequences for i in range(0, len(y), length)]
    if not parts:
        return LineCRF()
    n, width = len(parts), len(FEATURES)
    x, y, on = np.zeros((n, length, width)), np.zeros((n, length), int), np.zeros((n, length), bool)
    for i, (a, b) in enumerate(parts):
        x[i, : len(b)], y[i, : len(b)], on[i, : len(b)] = a, b, True
    pairs = on[:, 1:]
    seen_step = np.array([[((y[:, :-1] == a) & (y[:, 1:] == b) & pairs).sum() for b in (0, 1)] for a in (0, 1)], float)
    seen_unary = np.einsum("ntf,nt->f", x, (y * on).astype(float))
    seen_start = np.bincount(y[:, 0], minlength=2).astype(float)
    theta, m, v = np.zeros(width + 6), np.zeros(width + 6), np.zeros(width + 6)
    lines = on.sum()
    for k in range(1, rounds + 1):
        w, step, start = theta[:width], theta[width : width + 4].reshape(2, 2), theta[width + 4 :]
        u = np.stack([np.zeros((n, length)), x @ w], axis=2)
        f, b = np.zeros((n, length, 2)), np.zeros((n, length, 2))
        f[:, 0] = start + u[:, 0]
        for t in range(1, length):
            new = np.logaddexp(f[:, t - 1, :1] + step[0], f[:, t - 1, 1:] + step[1]) + u[:, t]
            f[:, t] = np.where(on[:, t, None], new, f[:, t - 1])
        for t in range(length - 2, -1, -1):
            z = b[:, t + 1] + u[:, t + 1]
            new = np.logaddexp(step[:, 0] + z[:, :1], step[:, 1] + z[:, 1:])
            b[:, t] = np.where(on[:, t + 1, None], new, b[:, t + 1])
        norm = np.logaddexp(f[:, -1, 0], f[:, -1, 1])[:, None]
        p = np.exp(f + b - norm[..., None]) * on[..., None]
        edge = np.exp(f[:, :-1, :, None] + step + (u + b)[:, 1:, None, :] - norm[..., None, None]) * pairs[..., None, None]
        grad = np.concatenate([seen_unary - np.einsum("ntf,nt->f", x, p[..., 1]), (seen_step - edge.sum((0, 1))).ravel(), seen_start - p[:, 0].sum(0)]) / lines - ridge * theta
        m, v = 0.9 * m + 0.1 * grad, 0.99 * v + 0.01 * grad**2
        theta = theta + rate * (m / (1 - 0.9**k)) / (np.sqrt(v / (1 - 0.99**k)) + 1e-9)
    return LineCRF(theta[:width], theta[width : width + 4].reshape(2, 2), theta[width + 4 :])


def weak_states(x: np.ndarray, quality: int) -> np.ndarray:
    """The states that the lines of a labelled document are taught with."""
    return (x[:, 6] > 0) | (x[:, 3] > WEAK_SYMBOL_SHARE) | (quality == 0)


def train(docs: DataFrame, labels: DataFrame, max_fit_docs: int = 3000, max_fit_segments: int = 6000, length: int = 48) -> LineCRF:
    """Fit on at most max_fit_segments runs of `length` lines, of at most max_fit_docs labelled documents.

    Documents with the least crc32 of their doc_id are taken, of these the segments with the
    least crc32 of doc_id and place, so a long document is represented by some of its
    segments as well. A segment is at most 48 lines of 80 bytes; no more is collected.
    """
    ids = labels.select(F.col("doc_id").alias("_id"), F.col("quality").alias("_q")).where("_id IS NOT NULL AND _q IS NOT NULL").groupBy("_id").agg(F.min("_q").alias("_q"))
    sample = ids.orderBy(F.crc32(F.col("_id").cast("string").cast("binary")), "_id").limit(max_fit_docs)
    chosen = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(sample), F.col("doc_id") == F.col("_id"))

    def segments(rows):
        for batch in batches(rows, 8 << 20):
            out = []
            for i, q, text in zip(batch["doc_id"].to_pylist(), batch["_q"].to_pylist(), texts(batch["text"])):
                x, _, _ = line_features(text)
                y = weak_states(x, q)
                out += [(i, at, zlib.crc32(b"%d:%d" % (i, at)), x[at : at + length].astype("<f8").tobytes(), y[at : at + length].astype("u1").tobytes()) for at in range(0, len(x), length)]
            cols = list(zip(*out)) or [()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary()), strict=True)], ["doc_id", "at", "rank", "x", "y"])

    found = chosen.mapInArrow(segments, "doc_id long, at long, rank long, x binary, y binary")
    rows = found.orderBy("rank", "doc_id", "at", "x", "y").limit(max_fit_segments).collect()
    return fit([(np.frombuffer(r.x, "<f8").reshape(-1, len(FEATURES)), np.frombuffer(r.y, "u1")) for r in rows], length=length)


COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
ADDED = {**dict.fromkeys((*COUNTS, "content_words"), "long"), "base_failed": "boolean", "kept": "boolean"}
_RESULT = pa.struct([(k, pa.bool_() if t == "boolean" else pa.int64()) for k, t in ADDED.items()])


def judged(docs: DataFrame, crf: LineCRF, into: str, min_words: int = 50, max_repeat_percent: int = 50, min_content: float = 0.5) -> DataFrame:
    """docs with a struct column `into` of ADDED's fields, judged from the column `text`."""
    schema = StructType([*docs.schema, StructField(into, StructType.fromDDL(", ".join(f"{k} {t}" for k, t in ADDED.items())))])

    def run(rows):
        for batch in batches(rows, 8 << 20):
            out = []
            for text in texts(batch["text"]):
                found = text_counts(text)
                n, repeats = found["n_words"], found["n_repeat_words"]
                content = sum(k for k, s in zip(found["line_words"], crf.decode(found["lines"]), strict=True) if s == 0) if n else 0
                failed = n < min_words or 100 * repeats > max_repeat_percent * n
                out.append({**{c: found[c] for c in COUNTS}, "content_words": content, "base_failed": failed, "kept": not failed and content >= min_content * n})
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out, _RESULT)], [*batch.schema.names, into])

    return docs.mapInArrow(run, schema)


def judge(docs: DataFrame, crf: LineCRF, **options) -> DataFrame:
    """doc_id with its counts, words in content lines, base_failed and kept."""
    return judged(docs.select("doc_id", "text"), crf, "found", **options).select("doc_id", "found.*")


def keep_good(docs: DataFrame, crf: LineCRF, **options) -> DataFrame:
    """The rows of docs that are kept, with their own columns, whatever their names."""
    into = free_name(docs, "found")
    return judged(docs, crf, into, **options).where(f"`{into}`.kept").select(*(f"`{c}`" for c in docs.columns))
