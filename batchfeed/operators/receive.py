"""Receiver side: preprocessing as expressions, and data-parallel training."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window as W, functions as F

from ..functions.columns import rounded


def preprocess_text(docs: DataFrame, length: int = 200) -> DataFrame:
    """Decode, normalise white space and case, crop: doc_id, text, n_tokens."""
    t = F.substring(F.trim(F.regexp_replace(F.lower("text"), "[ \\t\\n\\r\\x0b\\x0c]+", " ")), 1, length)
    return docs.select("doc_id", t.alias("text")).withColumn("n_tokens", F.size(F.split("text", " ")).cast("long"))


def resize_vectors(vectors: DataFrame, width: int = 16) -> DataFrame:
    """Mean-pool each vector to `width` values: vec_id, place, value."""
    v = vectors.select("vec_id", F.posexplode("embedding").alias("i", "x")).withColumn("x", F.col("x").cast("double"))
    per = 64 // width
    return v.groupBy("vec_id", F.floor(F.col("i") / per).cast("long").alias("place")).agg(rounded(F.sum(F.floor(F.col("x") * 1e6 + 0.5)) / F.lit(1e6 * per)).alias("value"))


def normalize_vectors(vectors: DataFrame) -> DataFrame:
    """Zero mean, unit deviation within each vector, by higher-order functions."""
    x = F.transform("embedding", lambda a: a.cast("double"))
    n = F.size("embedding").cast("double")
    total = F.aggregate("x", F.lit(0.0), lambda a, b: a + b)
    v = vectors.select("vec_id", "label", x.alias("x"), n.alias("n")).withColumn("m", total / F.col("n"))
    dev = F.sqrt(F.aggregate("x", F.lit(0.0), lambda a, b: a + (b - F.col("m")) * (b - F.col("m"))) / F.col("n"))
    return v.withColumn("d", dev).select("vec_id", "label", F.transform("x", lambda a: (a - F.col("m")) / F.nullif("d", F.lit(0.0))).alias("x"), "m", "d")


def _gradient(weights: np.ndarray, x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, float]:
    """Summed gradient and loss of softmax regression."""
    z = x @ weights
    z -= z.max(1, keepdims=True)
    p = np.exp(z)
    p /= p.sum(1, keepdims=True)
    loss = -np.log(np.maximum(p[np.arange(len(y)), y], 1e-300)).sum()
    p[np.arange(len(y)), y] -= 1
    return x.T @ p, float(loss)


def _matrix(b: pa.RecordBatch, width: int) -> np.ndarray:
    """Embeddings of a batch, a row each."""
    e = b["embedding"]
    if e.null_count or (np.diff(e.offsets.to_numpy()) != width).any():
        raise ValueError(f"an embedding is null or not of {width} values")
    return np.asarray(e.flatten().to_numpy(zero_copy_only=False), float).reshape(-1, width)


def _walk(batches, weights: np.ndarray, rate: float):
    """Steps in ascending order, one after the other from weights: (loss of each, weights after the last)."""
    losses, now, g, loss, n = [], None, np.zeros(weights.shape), 0.0, 0
    for b in batches:
        if not b.num_rows:
            continue
        step, x, y = b["step"].to_numpy(), _matrix(b, len(weights)), b["label"].to_numpy()
        edge = [0, *(np.flatnonzero(np.diff(step)) + 1).tolist(), len(step)]
        for a, z in zip(edge, edge[1:]):
            if n and step[a] != now:
                weights = weights - rate / n * g
                losses.append(loss / n)
                g, loss, n = np.zeros(weights.shape), 0.0, 0
            more, add = _gradient(weights, x[a:z], y[a:z])
            now, g, loss, n = step[a], g + more, loss + add, n + z - a
    if n:
        weights = weights - rate / n * g
        losses.append(loss / n)
    return losses, weights


def train(examples: DataFrame, steps: int, epochs: int = 1, rate: float = 0.5, classes: int = 10, width: int = 64, wide: int = 4096) -> tuple[list[float], np.ndarray]:
    """Data-parallel softmax regression over examples(step, embedding, label), step by step, epoch by epoch.

    The rows are put in order of step once and kept. Steps of over `wide` rows on average are
    taken one a job: the weights are sent out, gradients are summed per partition and added up,
    and what comes back is one matrix per partition. A job costs more than the gradient of a
    smaller step, so there the weights go from partition to partition, and each takes the steps
    it holds, all rows of each, in their order. Both give the loss of each step and the weights.
    """
    spark = examples.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    rows = examples.select("step", "embedding", "label")
    apart = rows.count() > wide * steps
    rows = rows.repartitionByRange(parts, "step", *[F.hash("embedding")] * apart).sortWithinPartitions("step").persist()
    try:
        return (_steps_apart if apart else _steps_in_turn)(rows, steps, epochs, rate, np.zeros((width, classes)))
    finally:
        rows.unpersist()


def _steps_in_turn(rows: DataFrame, steps: int, epochs: int, rate: float, weights: np.ndarray) -> tuple[list[float], np.ndarray]:
    """Steps below `steps` of rows whose partitions are ascending ranges of them: a task for each partition and epoch."""
    spark, losses = rows.sparkSession, []
    rows = rows.where(F.col("step").between(0, steps - 1))
    places = sorted(r.at for r in rows.select(F.spark_partition_id().alias("at")).distinct().collect())
    for _ in range(epochs):
        for at in places:
            held = spark.sparkContext.broadcast(weights)

            def part(batches, held=held):
                found, after = _walk(batches, held.value, rate)
                yield pa.RecordBatch.from_arrays([pa.array([np.array(found).tobytes()], pa.binary()), pa.array([after.tobytes()], pa.binary())], ["losses", "weights"])

            (r,) = spark.sparkContext.runJob(rows.mapInArrow(part, "losses binary, weights binary").rdd, list, [at])
            held.unpersist()
            losses += np.frombuffer(r.losses).tolist()
            weights = np.frombuffer(r.weights).reshape(weights.shape)
    return losses, weights


def _steps_apart(rows: DataFrame, steps: int, epochs: int, rate: float, weights: np.ndarray) -> tuple[list[float], np.ndarray]:
    """A job for each step, over all partitions that have rows of it."""
    spark, losses = rows.sparkSession, []
    for k in [*range(steps)] * epochs:
        held = spark.sparkContext.broadcast(weights)

        def part(batches, held=held):
            g, loss, n = np.zeros(held.value.shape), 0.0, 0
            for b in batches:
                if b.num_rows:
                    more, add = _gradient(held.value, _matrix(b, len(g)), b["label"].to_numpy())
                    g, loss, n = g + more, loss + add, n + b.num_rows
            if n:
                yield pa.RecordBatch.from_arrays([pa.array([g.tobytes()], pa.binary()), pa.array([loss]), pa.array([n], pa.int64())], ["g", "loss", "n"])

        found = rows.where(F.col("step") == k).select("embedding", "label").mapInArrow(part, "g binary, loss double, n long").collect()
        held.unpersist()
        n = sum(r.n for r in found)
        if n:
            weights = weights - rate / n * sum(np.frombuffer(r.g).reshape(weights.shape) for r in found)
            losses.append(sum(r.loss for r in found) / n)
    return losses, weights


def train_reference(x: np.ndarray, y: np.ndarray, step: np.ndarray, rate: float = 0.5, classes: int = 10) -> tuple[list[float], np.ndarray]:
    """The same on one node."""
    weights, losses = np.zeros((x.shape[1], classes)), []
    for k in range(int(step.max()) + 1):
        on = step == k
        g, loss = _gradient(weights, x[on], y[on])
        weights = weights - rate / on.sum() * g
        losses.append(loss / on.sum())
    return losses, weights


def moving_average(trace: DataFrame, keys: list[str], width: int = 10) -> DataFrame:
    """Mean of each value and the width - 1 before it."""
    w = W.partitionBy(*keys).orderBy("iter").rowsBetween(1 - width, 0)
    return trace.withColumn("ma", F.sum("loss_u").over(w) / F.count("*").over(w))
