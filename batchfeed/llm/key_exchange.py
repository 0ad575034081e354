"""Asking the whole corpus about keys, block by block.

Documents are packed into blocks of bounded size. A block asks about its distinct
64-bit keys, each with a small value; the keys of all blocks meet in key partitions,
which combine the values and answer every block in the order of its question. A key
costs at most one entry for each block that holds it, so frequent keys make no hot
partition, and entries travel as delta-coded arrays, not as rows.

A block has at most `fan` rows in an exchange, whatever the number of key partitions:
where there are more, blocks ask coarse partitions, in each of which as many of them are
put together as make a block again, which asks finer ones, and so on. Rows thus grow in
proportion to the input (times the levels, its logarithm to the base of `fan`), and the
answers come back the same way. A second level, which starts where the input has more
than `fan` key partitions, shuffles and stores what is asked once more. Everything in memory is bounded by the size of a block
or of a key partition.

Blocks are written once, in the shared folder, so that all stages see the same ones.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, functions as F

from .common import batches, release, texts, written

BLOCK_SCHEMA = "block long, crc long, size long, doc_ids binary, doc_null binary, body binary"
ASK_SCHEMA = "part int, block long, crc long, payload binary"
ANSWER_SCHEMA = "block long, crc long, part int, payload binary"


def packed(a: np.ndarray) -> bytes:
    """Bytes of an array, plane by plane, compressed."""
    planes = np.ascontiguousarray(a.view(np.uint8).reshape(len(a), a.itemsize).T) if len(a) else np.zeros(0, np.uint8)
    return struct.pack("<cBI", a.dtype.kind.encode(), a.itemsize, len(a)) + zstandard.ZstdCompressor(level=1).compress(planes.tobytes())


def unpacked(data: bytes) -> np.ndarray:
    kind, size, n = struct.unpack_from("<cBI", data)
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(data[6:]), np.uint8).reshape(size, n) if n else np.zeros((size, 0), np.uint8)
    if n < 2048:
        raw = np.ascontiguousarray(planes.T)
    else:  # numpy turns a large array slowly as a whole
        raw = np.empty((n, size), np.uint8)
        for i, plane in enumerate(planes):
            raw[:, i] = plane
    return raw.reshape(-1).view(f"<{kind.decode()}{size}")


def joined(parts: list[bytes]) -> bytes:
    return struct.pack(f"<I{len(parts)}I", len(parts), *map(len, parts)) + b"".join(parts)


def cut(data: bytes) -> list[bytes]:
    n = struct.unpack_from("<I", data)[0]
    out, at = [], 4 + 4 * n
    for size in struct.unpack_from(f"<{n}I", data, 4):
        out.append(data[at : at + size])
        at += size
    return out


def packed_keys(keys: np.ndarray) -> bytes:
    """Ascending uint64 keys as packed differences."""
    return packed(np.diff(keys, prepend=np.uint64(0)))


def unpacked_keys(data: bytes) -> np.ndarray:
    return np.cumsum(unpacked(data), dtype=np.uint64)


class Block:
    """Documents of a block: ids and texts."""

    def __init__(self, number: int, crc: int, doc_ids: np.ndarray, doc_null: np.ndarray, body: bytes):
        self.number, self.crc, self.doc_ids, self.doc_null = number, crc, doc_ids, doc_null
        raw = zstandard.ZstdDecompressor().decompress(body)
        sizes = np.frombuffer(raw, "<u8", len(doc_ids))
        at = 8 * len(doc_ids)
        self.texts = []
        for n in sizes.tolist():
            self.texts.append(raw[at : at + n])
            at += n

    @classmethod
    def of(cls, row: dict) -> Block:
        return cls(row["block"], row["crc"], np.frombuffer(row["doc_ids"], "<i8"), np.frombuffer(row["doc_null"], "u1"), row["body"])


def blocks(docs: DataFrame, block_bytes: int = 5 << 20) -> DataFrame:
    """Rows of docs(doc_id, text) packed into blocks of about block_bytes (one document at least)."""

    def run(rows):
        part, serial = TaskContext.get().partitionId(), 0
        ids, held, size = [], [], 0

        def close():
            raw = np.array([len(t) for t in held], "<u8").tobytes() + b"".join(held)
            numbers = np.array([0 if i is None else i for i in ids], "<i8").tobytes()
            body = zstandard.ZstdCompressor(level=3).compress(raw)
            return pa.RecordBatch.from_pydict({"block": pa.array([(part << 24) + serial], pa.int64()), "crc": pa.array([zlib.crc32(raw, zlib.crc32(numbers))], pa.int64()), "size": pa.array([len(raw)], pa.int64()), "doc_ids": pa.array([numbers], pa.binary()), "doc_null": pa.array([bytes(i is None for i in ids)], pa.binary()), "body": pa.array([body], pa.binary())})

        for batch in batches(rows, 2 << 20):
            for i, t in zip(batch["doc_id"].to_pylist(), texts(batch["text"]), strict=True):
                if held and size + len(t) > block_bytes:
                    yield close()
                    serial, ids, held, size = serial + 1, [], [], 0
                ids.append(i)
                held.append(t)
                size += len(t)
        if held:
            yield close()

    return written(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, BLOCK_SCHEMA), "blocks")


def block_rows(batch: pa.RecordBatch) -> Iterator[Block]:
    for row in batch.to_pylist():
        yield Block.of(row)


def part_of(keys: np.ndarray, parts: int) -> np.ndarray:
    """The part of each key; ascending in the key. parts < 2**32."""
    return ((keys >> np.uint64(32)) * np.uint64(parts) >> np.uint64(32)).astype(np.int64)


def ladder(parts: int, fan: int) -> list[int]:
    """Numbers of parts by level, the last `parts`, each at most about fan times the one before."""
    out = [parts]
    while out[0] > fan:
        out.insert(0, -(-out[0] // fan))
    return out


@dataclass(frozen=True)
class Exchange:
    """Key parts by level and the number of blocks that ask."""

    levels: tuple[int, ...]
    blocks: int
    text_bytes: int = 0

    @classmethod
    def over(cls, docs_blocks: DataFrame, part_bytes: int, fan: int = 4096, least: int = 48) -> Exchange:
        """As many parts as the text in docs_blocks has part_bytes, `least` at least."""
        n, size = docs_blocks.agg(F.count("*"), F.sum("size")).first()
        return cls(tuple(ladder(max(least, -(-(size or 0) // part_bytes)), fan)), max(n, 1), size or 0)

    def release(self, spark: SparkSession) -> None:
        """Have the files of a finished exchange removed, if they are large enough to wait a second for."""
        if self.text_bytes >= 128 << 20:
            release(spark)

    @property
    def first(self) -> int:
        return self.levels[0]

    @property
    def last(self) -> int:
        return self.levels[-1]


def ask_rows(number: int, crc: int, keys: np.ndarray, values: list[np.ndarray], parts: int) -> pa.RecordBatch:
    """ASK rows of ascending keys with values of the same order, one a part that has keys."""
    part = part_of(keys, parts)
    starts = np.flatnonzero(np.append(True, part[1:] != part[:-1])) if len(keys) else np.zeros(0, np.int64)
    bounds = np.append(starts, len(keys)).tolist()
    load = [joined([packed_keys(keys[a:z]), *(packed(np.ascontiguousarray(v[a:z])) for v in values)]) for a, z in zip(bounds, bounds[1:])]
    n = len(load)
    return pa.RecordBatch.from_arrays([pa.array(part[starts], pa.int32()), pa.array([number] * n, pa.int64()), pa.array([crc] * n, pa.int64()), pa.array(load, pa.binary())], ["part", "block", "crc", "payload"])


def asked(block: Block, keys: np.ndarray, values: list[np.ndarray], exchange: Exchange) -> pa.RecordBatch:
    """What a block asks: its ascending keys with values of the same order."""
    return ask_rows(block.number, block.crc, keys, values, exchange.first)


def _merged(asks: DataFrame, parts: int, finer: int, groups: int) -> DataFrame:
    """Blocks that ask one part put together by group: ASK rows of the finer parts, and how to take them apart."""

    def run(table: pa.Table) -> pa.Table:
        rows = sorted(table.to_pylist(), key=lambda r: r["block"])
        loads = [cut(r["payload"]) for r in rows]
        keys = [unpacked_keys(x[0]) for x in loads]
        sizes = np.array([len(k) for k in keys], np.int64)
        flat = np.concatenate(keys)
        order = np.argsort(flat, kind="stable")
        values = [np.concatenate([unpacked(x[i]) for x in loads])[order] for i in range(1, len(loads[0]))]
        part, number = rows[0]["part"], rows[0]["part"] * groups + rows[0]["g"]
        asks = ask_rows(number, 0, flat[order], values, finer)
        state = joined([packed(np.array([r["block"] for r in rows], np.int64)), packed(np.array([r["crc"] for r in rows], np.int64)), packed(sizes), packed(order.astype(np.uint32))])
        n = asks.num_rows
        return pa.table({
            "kind": pa.array(["state"] + ["ask"] * n), "part": pa.concat_arrays([pa.array([part], pa.int32()), asks["part"]]), "block": pa.array(np.full(1 + n, number)),
            "crc": pa.array(np.zeros(1 + n, np.int64)), "payload": pa.concat_arrays([pa.array([state], pa.binary()), asks["payload"]]),
        })

    return asks.withColumn("g", F.pmod(F.xxhash64("block"), F.lit(groups))).groupBy("part", "g").applyInArrow(run, f"kind string, {ASK_SCHEMA}")


def _apart(answers: DataFrame, states: DataFrame) -> DataFrame:
    """Answers to blocks put together as answers to each of them."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        out, got = [], right.to_pylist()
        for row in left.to_pylist():
            blocks, crcs, sizes, order = (unpacked(x) for x in cut(row["payload"]))
            values = []
            for v in values_in_order(got, 0):
                back = np.empty_like(v)
                back[order] = v
                values.append(back)
            ends = np.cumsum(sizes)
            out += [(b, c, row["part"], joined([packed(np.ascontiguousarray(v[z - n : z])) for v in values])) for b, c, n, z in zip(blocks.tolist(), crcs.tolist(), sizes.tolist(), ends.tolist(), strict=True)]
        return _answer_table(out)

    back = states.groupBy("block").cogroup(answers.where("block >= 0").groupBy("block")).applyInArrow(run, ANSWER_SCHEMA)
    return back.unionByName(answers.where("block < 0"))


def _answer_table(rows: list[tuple]) -> pa.Table:
    block, crc, part, payload = zip(*rows, strict=True) if rows else ((), (), (), ())
    return pa.table([pa.array(block, pa.int64()), pa.array(crc, pa.int64()), pa.array(part, pa.int32()), pa.array(payload, pa.binary())], names=["block", "crc", "part", "payload"])


def _routed(asks: DataFrame, exchange: Exchange, answer_last: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Carry asks through the levels, have them answered at the last, and carry the answers back."""
    states, blocks = [], exchange.blocks
    for parts, finer in zip(exchange.levels, exchange.levels[1:]):
        groups = -(-blocks // parts)
        blocks = groups * parts
        both = written(_merged(asks, parts, finer, groups), "merged")
        states.append(both.where("kind = 'state'").drop("kind"))
        asks = both.where("kind = 'ask'").drop("kind")
    answers = answer_last(asks)
    for state in reversed(states):
        answers = _apart(written(answers, "answers"), state)
    return answers


def answered(asks: DataFrame, exchange: Exchange, answer: Callable[[np.ndarray, np.ndarray, list[np.ndarray]], tuple[list[np.ndarray], list[np.ndarray]]]) -> DataFrame:
    """Combine the asks of each part and answer them.

    answer(keys, place, values) gets the part's distinct keys, for each entry its key's
    place among them, and the entries' values, blocks one after the other in ascending
    order; it returns arrays with a value for each entry, and arrays of any length that
    go to no block as a second list. They come as `block` -1 rows.
    """

    def run(table: pa.Table) -> pa.Table:
        rows = sorted(table.to_pylist(), key=lambda r: r["block"])
        loads = [cut(r["payload"]) for r in rows]
        keys = [unpacked_keys(x[0]) for x in loads]
        sizes = np.array([len(k) for k in keys])
        values = [np.concatenate([unpacked(x[i]) for x in loads]) for i in range(1, len(loads[0]))]
        del loads
        distinct, place = np.unique(np.concatenate(keys), return_inverse=True)
        per_entry, rest = answer(distinct, place, values)
        ends = np.cumsum(sizes)
        out = [(r["block"], r["crc"], r["part"], joined([packed(np.ascontiguousarray(v[z - n : z])) for v in per_entry])) for r, n, z in zip(rows, sizes, ends, strict=True)]
        if rest:
            out.append((-1, 0, rows[0]["part"], joined([packed(v) for v in rest])))
        return _answer_table(out)

    return _routed(asks, exchange, lambda last: last.groupBy("part").applyInArrow(run, ANSWER_SCHEMA))


def with_part(table: DataFrame, parts: int) -> DataFrame:
    """table(key long, value double) with the part of each key."""

    def run(rows):
        for batch in rows:
            keys = batch["key"].to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)
            yield pa.RecordBatch.from_arrays([pa.array(part_of(keys, parts).astype(np.int32)), batch["key"], batch["value"]], ["part", "key", "value"])

    return table.select("key", "value").mapInArrow(run, "part int, key long, value double")


def looked_up(asks: DataFrame, table: DataFrame, exchange: Exchange, default: float = 0.0) -> DataFrame:
    """Answer asks, which carry keys alone, from table(key, value); unknown keys get the default."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        keys = right["key"].to_numpy().astype(np.int64).view(np.uint64)
        order = np.argsort(keys)
        keys, values = np.append(keys[order], np.uint64(0)), np.append(right["value"].to_numpy()[order], default)
        out = []
        for r in left.to_pylist():
            q = unpacked_keys(cut(r["payload"])[0])
            at = np.searchsorted(keys[:-1], q)
            out.append((r["block"], r["crc"], r["part"], joined([packed(np.where((keys[at] == q) & (at < len(keys) - 1), values[at], default))])))
        return _answer_table(out)

    return _routed(asks, exchange, lambda last: last.groupBy("part").cogroup(with_part(table, exchange.last).groupBy("part")).applyInArrow(run, ANSWER_SCHEMA))


def values_in_order(rows: list[dict], crc: int) -> list[np.ndarray]:
    """The answers to one block as arrays in the order of its keys; none if it had no keys."""
    rows = sorted(rows, key=lambda r: r["part"])
    if any(r["crc"] != crc for r in rows):
        raise ValueError("answers to another block")
    loads = [[unpacked(x) for x in cut(r["payload"])] for r in rows]
    return [np.concatenate(v) for v in zip(*loads, strict=True)]


def meet(docs_blocks: DataFrame, answers: DataFrame, use: Callable[[Block, dict[int, list[np.ndarray]]], pa.Table], schema: str) -> DataFrame:
    """Bring each block's answers to it.

    answers has a column `level`; use(block, answers by level) returns a table of schema.
    """

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        out, by_level = [], {}
        for r in right.to_pylist():
            by_level.setdefault(r["level"], []).append(r)
        for block in block_rows(left):
            out.append(use(block, {k: values_in_order(v, block.crc) for k, v in by_level.items()}))
        if not out:
            raise ValueError("answers to a block that is not there")
        return pa.concat_tables(out)

    return docs_blocks.groupBy("block").cogroup(answers.where("block >= 0").groupBy("block")).applyInArrow(run, schema)
