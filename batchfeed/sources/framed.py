"""Shard files: records one after the other, each behind a header, and reading blocks of them.

A header has 16 bytes, little endian: length u64, CRC-32 of the body u32, label i32. A
file holds records of one shard in record order; a large shard has several files, since
the writers share it by ranges of record_id.
"""

from __future__ import annotations

import posixpath
import struct
import uuid
import zlib

import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..functions.columns import div
from .storage import file_system, make_folder, new_path, written

HEADER = "<QIi"
HEADER_BYTES = struct.calcsize(HEADER)
INDEX_SCHEMA = "shard_id string, file string, record_id long, position long, size long, label int"


def write_shards(records: DataFrame, folder: str, partitions: int, file_bytes: int = 64 << 20) -> DataFrame:
    """Write records(shard_id, record_id, label, body) to folder; a row of INDEX_SCHEMA for each.

    The list of what was written is itself stored, so files of failed attempts are never read.
    """
    ordered = records.select("shard_id", F.col("record_id").cast("long"), F.coalesce("label", F.lit(-1)).cast("int").alias("label"), F.coalesce("body", F.lit(b"")).alias("body"))
    ordered = ordered.repartitionByRange(partitions, "shard_id", "record_id").sortWithinPartitions("shard_id", "record_id", "body")

    def run(rows):
        fs, root = make_folder(folder)
        shard, name, out, at = None, None, None, 0
        for batch in rows:
            index = []
            for s, record, label, body in zip(*(batch[c].to_pylist() for c in ("shard_id", "record_id", "label", "body")), strict=True):
                if out is None or s != shard or at >= file_bytes:
                    if out is not None:
                        out.close()
                    shard, name, at = s, f"{uuid.uuid4().hex}.shard", 0
                    out = fs.open_output_stream(posixpath.join(root, name), compression=None)
                out.write(struct.pack(HEADER, len(body), zlib.crc32(body), label))
                out.write(body)
                index.append((s, name, record, at, len(body), label))
                at += HEADER_BYTES + len(body)
            cols = list(zip(*index)) or [()] * 6
            types = (pa.string(), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.int32())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], ["shard_id", "file", "record_id", "position", "size", "label"])
        if out is not None:
            out.close()

    return written(ordered.mapInArrow(run, INDEX_SCHEMA), "shard-files")


def blocks_of(plan: DataFrame, index: DataFrame, batch: int) -> DataFrame:
    """The contiguous reads of a plan: plan's columns with file, block_start, block_end, first and n_block.

    index(shard_id, ordinal, file, position, size). A range of at most `batch` records touches two
    cells of the index, so this is an equality join; where a range crosses files it is a block in each.
    """
    cells = plan.withColumn("_cell", F.explode(F.sequence(div(F.col("first_ordinal"), batch), div(F.col("first_ordinal") + F.col("n") - 1, batch))))
    keyed = index.select(F.col("shard_id"), F.col("ordinal").alias("_o"), "file", "position", "size", div(F.col("ordinal"), batch).alias("_cell"))
    hit = cells.join(keyed, ["shard_id", "_cell"]).where((F.col("_o") >= F.col("first_ordinal")) & (F.col("_o") < F.col("first_ordinal") + F.col("n")))
    ends = F.col("position") + F.col("size") + HEADER_BYTES
    return hit.groupBy(*plan.columns, "file").agg(F.min("position").alias("block_start"), F.max(ends).alias("block_end"), F.min("_o").alias("first"), F.count("*").alias("n_block"))


def parse_block(data: bytes) -> list[tuple[int, bytes]]:
    """(label, body) of the records of a block."""
    out, at = [], 0
    while at < len(data):
        size, crc, label = struct.unpack_from(HEADER, data, at)
        body = data[at + HEADER_BYTES : at + HEADER_BYTES + size]
        if len(body) != size or zlib.crc32(body) != crc:
            raise ValueError(f"the record at byte {at} of a block is damaged")
        out.append((label, body))
        at += HEADER_BYTES + size
    return out


def read_blocks(blocks: DataFrame, folder: str) -> DataFrame:
    """epoch, node_id, worker, batch_seq, shard_id, ordinal, label, body: one seek and one read a block."""
    keys = ["epoch", "node_id", "worker", "batch_seq", "shard_id"]
    near = blocks.select(*(F.col(k).cast("long").alias(k) for k in keys[:4]), "shard_id", "file", "block_start", "block_end", "first")

    def run(rows):
        fs, root = file_system(folder)
        name, held = None, None
        for batch in rows:
            for r in batch.to_pylist():
                if r["file"] != name:
                    if held is not None:
                        held.close()
                    name, held = r["file"], fs.open_input_file(posixpath.join(root, r["file"]))
                held.seek(r["block_start"])
                found = parse_block(held.read(r["block_end"] - r["block_start"]))
                n = len(found)
                yield pa.RecordBatch.from_arrays([*(pa.array([r[k]] * n, pa.int64()) for k in keys[:4]), pa.array([r["shard_id"]] * n, pa.string()), pa.array(range(r["first"], r["first"] + n), pa.int64()), pa.array([x for x, _ in found], pa.int32()), pa.array([x for _, x in found], pa.binary())], [*keys, "ordinal", "label", "body"])
        if held is not None:
            held.close()

    schema = "epoch long, node_id long, worker long, batch_seq long, shard_id string, ordinal long, label int, body binary"
    return near.sortWithinPartitions("file", "block_start").mapInArrow(run, schema)


def build_shards(records: DataFrame, partitions: int) -> tuple[str, DataFrame]:
    """Shard files of records in the shared folder: the folder and the list of its records."""
    folder = new_path(records.sparkSession, "shards")
    return folder, write_shards(records, folder, partitions)
