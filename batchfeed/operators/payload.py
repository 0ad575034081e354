"""Payloads: a batch of records as one binary value, and back.

framed: big-endian u32 length, then bytes, for each record. msgpack: an array of bin
values by the public format. Both are built from Catalyst expressions over the ordered
records of a batch; reading them needs Python. arrow: an IPC stream of one column.
"""

from __future__ import annotations

import struct

import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from .planner import div


def _hex(n: Column, width: int) -> Column:
    return F.unhex(F.lpad(F.hex(n.cast("long")), width, "0"))


def framed_record(body: Column) -> Column:
    return F.concat(_hex(F.octet_length(body), 8), body)


def msgpack_bin(body: Column) -> Column:
    """bin8, bin16 or bin32 by length."""
    n = F.octet_length(body)
    head = F.when(n < 256, F.concat(F.unhex(F.lit("C4")), _hex(n, 2))).when(n < 65536, F.concat(F.unhex(F.lit("C5")), _hex(n, 4))).otherwise(F.concat(F.unhex(F.lit("C6")), _hex(n, 8)))
    return F.concat(head, body)


def msgpack_array(n: Column) -> Column:
    """fixarray, array16 or array32 by count."""
    return F.when(n < 16, _hex(n + 0x90, 2)).when(n < 65536, F.concat(F.unhex(F.lit("DC")), _hex(n, 4))).otherwise(F.concat(F.unhex(F.lit("DD")), _hex(n, 8)))


def pack(samples: DataFrame, batch: int, codec: str = "framed") -> DataFrame:
    """Payloads of samples(shard_id, ordinal, body): shard_id, batch_seq, n_records, body.

    A group is one batch, so it holds at most `batch` records.
    """
    cell = samples.withColumn("batch_seq", div(F.col("ordinal"), batch)).groupBy("shard_id", "batch_seq")
    rows = cell.agg(F.array_sort(F.collect_list(F.struct("ordinal", F.coalesce("body", F.unhex(F.lit(""))).alias("body")))).alias("rows"))
    one = framed_record if codec == "framed" else msgpack_bin
    parts = F.transform("rows", lambda r: one(r["body"]))
    body = F.aggregate(parts, F.unhex(F.lit("")), lambda a, x: F.concat(a, x))
    n = F.size("rows").cast("long")
    if codec == "msgpack":
        body = F.concat(msgpack_array(n), body)
    return rows.select("shard_id", "batch_seq", n.alias("n_records"), body.alias("body"))


def records_of(body: bytes, codec: str) -> list[bytes]:
    """The records of a payload."""
    out, at = [], 0
    if codec == "framed":
        while at < len(body):
            n = struct.unpack_from(">I", body, at)[0]
            out.append(body[at + 4 : at + 4 + n])
            at += 4 + n
        return out
    if codec == "arrow":
        return pa.ipc.open_stream(body).read_all()["body"].to_pylist()
    first = body[0]
    count, at = (first & 15, 1) if first >> 4 == 9 else (struct.unpack_from(">H", body, 1)[0], 3) if first == 0xDC else (struct.unpack_from(">I", body, 1)[0], 5)
    widths = {0xC4: (">B", 2), 0xC5: (">H", 3), 0xC6: (">I", 5)}
    for _ in range(count):
        kind, head = widths[body[at]]
        n = struct.unpack_from(kind, body, at + 1)[0]
        out.append(body[at + head : at + head + n])
        at += head + n
    return out


def unpack(payloads: DataFrame, batch: int, codec: str = "framed") -> DataFrame:
    """shard_id, ordinal, body of every record."""

    def run(rows):
        for b in rows:
            out = [(s, q * batch + i, x) for s, q, body in zip(b["shard_id"].to_pylist(), b["batch_seq"].to_pylist(), b["body"].to_pylist(), strict=True) for i, x in enumerate(records_of(body, codec))]
            c = list(zip(*out, strict=True)) or [()] * 3
            yield pa.RecordBatch.from_arrays([pa.array(c[0], pa.string()), pa.array(c[1], pa.int64()), pa.array(c[2], pa.binary())], ["shard_id", "ordinal", "body"])

    return payloads.select("shard_id", "batch_seq", "body").mapInArrow(run, "shard_id string, ordinal long, body binary")


def to_arrow(payloads: DataFrame) -> DataFrame:
    """The framed payloads as Arrow IPC streams of one column."""

    def run(rows):
        for b in rows:
            bodies = []
            for body in b["body"].to_pylist():
                sink = pa.BufferOutputStream()
                t = pa.table({"body": pa.array(records_of(body, "framed"), pa.binary())})
                with pa.ipc.new_stream(sink, t.schema) as w:
                    w.write_table(t)
                bodies.append(sink.getvalue().to_pybytes())
            yield pa.RecordBatch.from_arrays([b["shard_id"], b["batch_seq"], b["n_records"], pa.array(bodies, pa.binary())], ["shard_id", "batch_seq", "n_records", "body"])

    return payloads.mapInArrow(run, payloads.schema)


class UnpackRecords:
    """A table function: the records of one payload, with their places in it."""

    def eval(self, body: bytes, codec: str):
        yield from enumerate(records_of(bytes(body), codec))


def register_unpack(spark, name: str = "unpack_records") -> None:
    """Make the table function known to SQL."""
    spark.udtf.register(name, F.udtf(UnpackRecords, returnType="place int, body binary"))
