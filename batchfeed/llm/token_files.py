"""Token ids in files coded by a static range asymmetric numeral system.

A file holds one frequency table, shared by its independent blocks. A block spreads its
tokens over interleaved lanes, each a coder state of its own; numpy steps all lanes of
all blocks at once. The block index is the list of checkpoints: offset, length and
checksum of each block, so any block decodes alone and a damaged one is found.

Layout (little endian): magic, a JSON header with section lengths, then the sections:
symbols u32, frequencies u32 (sum 2**SCALE), document ids i64 and null marks u8,
document lengths u32, block lengths u32, block word counts u32, block crc32 u32, lane
states u64, code words u32.

Documents are range-partitioned and sorted by doc_id, so the files' order is the ids'
order. Edge cases: null and empty texts are the end id alone; null doc_ids come first;
rows of a repeated doc_id are written one after the other; an empty table writes no file.
"""

from __future__ import annotations

import gc
import json
import os
import posixpath
import re
import struct
import uuid
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window as W, functions as F

from .common import batches, new_path, partitions_for, written

MAGIC = b"BFTOK1\n\0"
SCALE, LANES, BLOCK_TOKENS = 20, 32, 1 << 15
_LOW = np.uint64(1 << 31)
SECTIONS = (("symbols", "<u4"), ("freqs", "<u4"), ("doc_ids", "<i8"), ("doc_null", "u1"), ("doc_tokens", "<u4"), ("block_tokens", "<u4"), ("block_words", "<u4"), ("block_crc", "<u4"), ("states", "<u8"), ("words", "<u4"))


def scaled(counts: np.ndarray, total: int = 1 << SCALE) -> np.ndarray:
    """Frequencies of at least 1 that sum to total, near to the counts' shares."""
    f = np.maximum(1, (counts.astype(np.float64) * (total / counts.sum())).astype(np.int64))
    rest = total - int(f.sum())
    while rest:
        top = int(f.argmax())
        step = rest if rest > 0 else -min(-rest, int(f[top] + 1) // 2)
        f[top] += step
        rest -= step
    return f


def _coded(grid: np.ndarray, freq: np.ndarray, start: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Lane states, code words and numbers of words of blocks of tokens, grid(block, step, lane)."""
    n_blocks, steps, _ = grid.shape
    x = np.full((n_blocks, LANES), _LOW)
    out = np.zeros(grid.shape, np.uint32)
    sent = np.zeros(grid.shape, bool)
    scale, word, room = np.uint64(SCALE), np.uint64(32), np.uint64(63 - SCALE)
    for s in range(steps - 1, -1, -1):
        t = grid[:, s]
        f = freq[t]
        full = x >= (f << room)
        out[:, s] = x.astype(np.uint32)
        sent[:, s] = full
        x = np.where(full, x >> word, x)
        q = x // f
        x = (q << scale) + (x - q * f) + start[t]
    return x.ravel(), out[sent], sent.sum((1, 2))


def encode_file(ids: np.ndarray, doc_ids: list[int | None], doc_tokens: list[int], group: int = 128) -> bytes:
    """A file of the given ids (not empty) of the given documents; `group` blocks are coded at a time."""
    counts = np.bincount(ids)
    symbols = np.flatnonzero(counts)
    freqs = scaled(counts[symbols])
    freq, start = np.zeros(len(counts), np.uint64), np.zeros(len(counts), np.uint64)
    freq[symbols] = freqs
    start[symbols] = np.cumsum(freqs) - freqs
    n_blocks = -(-len(ids) // BLOCK_TOKENS)
    steps = BLOCK_TOKENS // LANES if n_blocks > 1 else -(-len(ids) // LANES)
    size = steps * LANES
    coded = []
    for at in range(0, n_blocks, group):
        mine = ids[at * size : (at + group) * size]
        padded = np.full(-(-len(mine) // size) * size, symbols[freqs.argmax()], ids.dtype)
        padded[: len(mine)] = mine
        coded.append(_coded(padded.reshape(-1, steps, LANES), freq, start))
    states, words, sent = (np.concatenate(c) for c in zip(*coded, strict=True))
    lengths = np.full(n_blocks, size)
    lengths[-1] = len(ids) - (n_blocks - 1) * size
    ends = np.cumsum(lengths)
    parts = {
        "symbols": symbols, "freqs": freqs, "doc_ids": [0 if i is None else i for i in doc_ids], "doc_null": [i is None for i in doc_ids], "doc_tokens": doc_tokens,
        "block_tokens": lengths, "block_words": sent, "block_crc": [zlib.crc32(ids[b - a : b].astype("<u4").tobytes()) for a, b in zip(lengths, ends, strict=True)],
        "states": states, "words": words,
    }
    data = [np.asarray(parts[k], kind).tobytes() for k, kind in SECTIONS]
    head = json.dumps({"lanes": LANES, "scale": SCALE, "steps": steps, "sizes": [len(d) for d in data]}).encode()
    return MAGIC + struct.pack("<I", len(head)) + head + b"".join(data)


def decode_file(data: bytes | pa.Buffer, only: list[int] | None = None, group: int = 128) -> tuple[np.ndarray, list[int | None], np.ndarray]:
    """ids, doc_ids and tokens per document of a file; only: ids of these blocks alone. `group` blocks are decoded at a time."""
    data = memoryview(data)
    if data[: len(MAGIC)] != MAGIC:
        raise ValueError("not a token file")
    size = struct.unpack_from("<I", data, len(MAGIC))[0]
    at = len(MAGIC) + 4
    head = json.loads(bytes(data[at : at + size]))
    at += size
    part = {}
    for (name, kind), n in zip(SECTIONS, head["sizes"], strict=True):
        part[name] = np.frombuffer(data, kind, n // np.dtype(kind).itemsize, at)
        at += n
    freqs = part["freqs"].astype(np.int64)
    slot_of = np.repeat(np.arange(len(freqs), dtype=np.uint32), freqs)
    freq, start = freqs.astype(np.uint64), (np.cumsum(freqs) - freqs).astype(np.uint64)
    lanes, steps, scale = head["lanes"], head["steps"], np.uint64(head["scale"])
    first = np.cumsum(part["block_words"].astype(np.int64)) - part["block_words"]
    words, mask = part["words"], np.uint64((1 << head["scale"]) - 1)
    chosen = np.arange(len(part["block_tokens"])) if only is None else np.asarray(only)
    out = np.empty(int(part["block_tokens"][chosen].sum()), np.uint32)
    done = 0
    for at in range(0, len(chosen), group):
        mine = chosen[at : at + group]
        pointer = first[mine]
        x = part["states"].reshape(-1, lanes)[mine].copy()
        grid = np.empty((len(mine), steps, lanes), np.uint32)
        for s in range(steps):
            low = x & mask
            t = slot_of[low.astype(np.int64)]
            grid[:, s] = t
            x = freq[t] * (x >> scale) + low - start[t]
            need = x < _LOW
            order = np.cumsum(need, axis=1)
            where = np.minimum(pointer[:, None] + order - 1, len(words) - 1)
            x = np.where(need, (x << np.uint64(32)) | (words[where] if len(words) else np.uint64(0)), x)
            pointer = pointer + order[:, -1]
        for i, b in enumerate(mine):
            n = int(part["block_tokens"][b])
            row = part["symbols"][grid[i].ravel()[:n]]
            if zlib.crc32(row.astype("<u4").tobytes()) != part["block_crc"][b]:
                raise ValueError(f"block {b} is damaged")
            out[done : done + n] = row
            done += n
    doc_ids = [None if z else int(i) for i, z in zip(part["doc_ids"], part["doc_null"], strict=True)]
    return out, doc_ids, part["doc_tokens"].astype(np.int64)


class CachedTokenizer:
    """The tokenizers library behind a cache of units between single spaces and newlines.

    A byte-level pre-tokenizer never joins text across a space that stands between two
    non-space characters, except that the space leads the next unit; a newline there is a
    piece of its own, and so is each of two. So units encode alone, newlines leading the unit
    after them, and a text's ids are those of its units. Texts with other white space, which
    `_ODD` finds, are cut at their spaces between non-space characters only.
    """

    _CUT = re.compile(r"(?<=\S) (?=\S)")
    _ODD = r"\A | \z|  | \n|\n |\n\n\n|\n\n\z|[\t\x0b\x0c\r\x1c-\x1f\x{85}\x{a0}\x{1680}\x{2000}-\x{200a}\x{2028}\x{2029}\x{202f}\x{205f}\x{3000}]"
    _MARKS = ".,;:!?|*#$%&)"

    def __init__(self, path: str, limit: int = 500_000):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # a task has one core; idle threads would spin
        from tokenizers import Tokenizer

        self.model = Tokenizer.from_file(path)
        self.kind = np.dtype("<u2" if self.model.get_vocab_size() <= 1 << 16 else "<u4")
        vocabulary = self.model.get_vocab()
        self.odd = "|".join([self._ODD, *(rf"\Q{t.content}\E" for t in self.model.get_added_tokens_decoder().values())])
        self.newline = self._alone(["\n"])[0]
        most = max(vocabulary.values(), default=0) + 1
        self.leads = {" ": np.zeros(most, bool), "\n": np.zeros(most, bool)}
        self.leads[" "][[i for t, i in vocabulary.items() if t.startswith("\u0120")]] = True
        self.leads["\n"][np.frombuffer(self.newline, self.kind)[:1]] = True
        # ids by unit, in two generations: the older one is dropped when the younger has half the limit,
        # and what is used meanwhile moves to the younger
        self.words: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}
        self.limit = limit

    def _alone(self, units: list[str]) -> list[bytes]:
        return [np.array(e.ids, self.kind).tobytes() for at in range(0, len(units), 4096) for e in self.model.encode_batch_fast(units[at : at + 4096], add_special_tokens=False)]

    def _learn(self, units: list[str]) -> None:
        """Encode units not known yet. Those led by their only space or newline go as one text, whose
        ids are cut again at the tokens that lead; that spares the library's cost per text."""
        known, older = self.words, self.older
        unseen = [u for u in units if u not in known]
        new = [u for u in unseen if u not in older] if older else unseen
        if len(new) < len(unseen):
            known.update((u, older[u]) for u in unseen if u in older)
        # the first unit of an odd text may start with white space, which must not meet the newline put before it
        apart = [u for u in new if u[0] == "\n" and not u[1:2].strip()]
        self.words.update(zip(apart, [self.newline + raw for raw in self._alone([u[1:] for u in apart])], strict=True))
        for lead, leads in self.leads.items():
            led = [u for u in new if u[0] == lead and lead not in u[1:]]
            for at in range(0, len(led), 2048):
                some = led[at : at + 2048]
                ids = np.array(self.model.encode_batch_fast(["".join(some)], add_special_tokens=False)[0].ids, self.kind)
                ends = np.append(np.flatnonzero(leads[ids]), len(ids)) * self.kind.itemsize
                if len(ends) == len(some) + 1 and not ends[0]:
                    raw, bounds = ids.tobytes(), ends.tolist()
                    self.words.update((u, raw[a:z]) for u, a, z in zip(some, bounds, bounds[1:]) if u not in self.words)
        rest = [u for u in new if u not in self.words]
        self.words.update(zip(rest, self._alone(rest), strict=True))

    def _known(self, units: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids of the distinct units end to end, and where each starts and how many it has."""
        distinct = units.to_numpy(zero_copy_only=False).tolist()
        self._learn(distinct)
        found = list(map(self.words.__getitem__, distinct))
        sizes = np.fromiter(map(len, found), np.int64, len(found)) // self.kind.itemsize
        return np.frombuffer(b"".join(found), self.kind), np.cumsum(sizes) - sizes, sizes

    def _units(self, units: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """As _known, of units whose trailing marks are encoded apart: after a letter they are a piece
        of their own for the pre-tokenizer, so a word is encoded once for all marks that follow it."""
        led = pc.if_else(pc.starts_with(units, "\n"), units, pc.binary_join_element_wise(_text(" "), units, _text("")))
        cores = pc.utf8_rtrim(led, self._MARKS)
        cores = pc.if_else(pc.match_substring_regex(cores, r"\pL\z"), cores, led)
        words = cores.dictionary_encode()
        marks = _after(led, cores).dictionary_encode()
        flat, start, size = self._known(words.dictionary)
        ends = self._alone(marks.dictionary.to_pylist())
        end_size = np.array([len(e) for e in ends], np.int64) // self.kind.itemsize
        end_start = len(flat) + np.cumsum(end_size) - end_size
        which, end = words.indices.to_numpy(zero_copy_only=False), marks.indices.to_numpy(zero_copy_only=False)
        starts = np.stack([start[which], end_start[end]], axis=1).ravel()
        sizes = np.stack([size[which], end_size[end]], axis=1).ravel()
        both = _gather(np.concatenate([flat, np.frombuffer(b"".join(ends), self.kind)]), starts, sizes)
        whole = sizes.reshape(-1, 2).sum(1)
        return both, np.cumsum(whole) - whole, whole

    def encode(self, batch: list[str | None] | pa.Array, piece: int = 1 << 18) -> list[bytes]:
        """Ids of each text (null: none), as little-endian bytes of self.kind."""
        if len(self.words) > self.limit // 2:
            self.older, self.words = self.words, {}
        texts = pc.fill_null(pa.array(batch, pa.large_string()) if isinstance(batch, list) else batch.cast(pa.large_string()), "")
        odd = pc.match_substring_regex(texts, self.odd)
        # a newline before each text shows that no space leads its first unit; its ids are dropped below
        plain = pc.split_pattern(pc.binary_join_element_wise(_text("\n"), pc.replace_substring(texts.filter(pc.invert(odd)), "\n", " \n"), _text("")), " ")
        cut = [["\n" + first, *others] for first, *others in map(self._CUT.split, texts.filter(odd).to_pylist())]
        units = pa.concat_arrays([plain.flatten(), pa.array([u for c in cut for u in c], pa.large_string())]).dictionary_encode()
        counts = np.concatenate([pc.list_value_length(plain).to_numpy(zero_copy_only=False), np.array([len(c) for c in cut], np.int64)]).astype(np.int64)
        flat, starts, sizes = self._units(units.dictionary)
        index = units.indices.to_numpy(zero_copy_only=False)
        raw = b"".join(_gather(flat, starts[i], sizes[i]).tobytes() for i in (index[at : at + piece] for at in range(0, len(index), piece)))
        unit_ends = np.append(0, np.cumsum(sizes[index])) * self.kind.itemsize
        bounds = unit_ends[np.append(0, np.cumsum(counts))].tolist()
        where = odd.to_numpy(zero_copy_only=False).astype(bool)
        out = [b""] * len(where)
        for k, a, z in zip(np.argsort(where, kind="stable").tolist(), bounds, bounds[1:]):
            out[k] = raw[a + len(self.newline) : z]
        return out


def _text(value: str) -> pa.Scalar:
    return pa.scalar(value, pa.large_string())


def _after(whole: pa.Array, heads: pa.Array) -> pa.Array:
    """What follows each head in the string that it starts."""
    ends, lengths = np.frombuffer(whole.buffers()[1], np.int64)[whole.offset : whole.offset + len(whole) + 1], pc.binary_length(heads).to_numpy(zero_copy_only=False)
    sizes = np.diff(ends) - lengths
    data = _gather(np.frombuffer(whole.buffers()[2], np.uint8), ends[:-1] + lengths, sizes)
    return pa.LargeStringArray.from_buffers(len(whole), pa.py_buffer(np.append(0, np.cumsum(sizes)).astype(np.int64)), pa.py_buffer(data))


def _gather(flat: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The ranges of flat that begin at starts, end to end."""
    at = np.repeat(starts - (np.cumsum(sizes) - sizes), sizes)
    at += np.arange(len(at))
    return flat[at]


_TOKENIZERS: dict[str, CachedTokenizer] = {}


def tokenizer(path: str) -> CachedTokenizer:
    """One cached tokenizer per Python worker and path."""
    if path not in _TOKENIZERS:
        _TOKENIZERS[path] = CachedTokenizer(path)
    return _TOKENIZERS[path]


def drop_tokenizers() -> None:
    """Free what the worker has cached; for tasks that come after the encoding."""
    if _TOKENIZERS:
        _TOKENIZERS.clear()
        gc.collect()


def write_files(docs: DataFrame, folder: str, tokenizer_path: str, end_id: int = 0, file_tokens: int = 4 << 20, partition_bytes: int = 12 << 20) -> DataFrame:
    """Encode docs(doc_id, text) into files in folder, in ascending doc_id order.

    Returns a row per file: name, part and serial (its place), documents, tokens.
    """
    parts = partitions_for(docs, partition_bytes, least=1)
    ordered = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").repartitionByRange(parts, F.col("doc_id").asc_nulls_first()).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "text")

    def run(rows):
        import contextlib

        t = tokenizer(tokenizer_path)
        end = np.array([end_id], t.kind).tobytes()
        fs, root = pafs.FileSystem.from_uri(folder)
        with contextlib.suppress(FileExistsError):
            fs.create_dir(root, recursive=True)
        part, serial, held, ids, lengths, total = TaskContext.get().partitionId(), 0, [], [], [], 0

        def close():
            name = f"{uuid.uuid4().hex}.tokens"
            with fs.open_output_stream(posixpath.join(root, name), compression=None) as out:
                out.write(encode_file(np.frombuffer(b"".join(held), t.kind), ids, lengths))
            return pa.RecordBatch.from_pydict({"name": [name], "part": pa.array([part], pa.int64()), "serial": pa.array([serial], pa.int64()), "documents": pa.array([len(ids)], pa.int64()), "tokens": pa.array([total], pa.int64())})

        for batch in batches(rows, 4 << 20):
            for i, raw in zip(batch["doc_id"].to_pylist(), t.encode(batch["text"]), strict=True):
                held.append(raw + end)
                ids.append(i)
                lengths.append(len(raw) // t.kind.itemsize + 1)
                total += lengths[-1]
                if total >= file_tokens:
                    yield close()
                    serial, held, ids, lengths, total = serial + 1, [], [], [], 0
        if ids:
            yield close()

    return ordered.mapInArrow(run, "name string, part long, serial long, documents long, tokens long")


def read_files(files: DataFrame, folder: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of the documents in the files that write_files listed.

    Places within the files are found first; the narrow rows, not the files, are then joined
    with the files' own places, which also leaves out files that failed attempts wrote. Only the list of
    files, one row each, is put in one order.
    """
    before = F.sum("tokens").over(W.orderBy("part", "serial").rowsBetween(W.unboundedPreceding, -1))
    placed = files.select("name", F.coalesce(before, F.lit(0)).cast("long").alias("offset"))
    listed = files.sparkSession.read.format("binaryFile").load(folder).select(F.element_at(F.split("path", "/"), -1).alias("name"), "content")

    def run(rows):
        drop_tokenizers()
        for batch in rows:
            for name, data in zip(batch["name"], batch["content"], strict=True):
                ids, doc_ids, sizes = decode_file(data.as_buffer())
                ends = np.cumsum(sizes)
                raw = memoryview(ids.astype("<u4", copy=False)).cast("B")
                crc = [zlib.crc32(raw[4 * (z - n) : 4 * z]) for z, n in zip(ends.tolist(), sizes.tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array([name.as_py()] * len(crc), pa.string()), pa.array(doc_ids, pa.int64()), pa.array(ends - sizes, pa.int64()), pa.array(sizes, pa.int64()), pa.array(crc, pa.int64())], ["name", "doc_id", "at", "n_tokens", "ids_crc32"])

    found = listed.mapInArrow(run, "name string, doc_id long, at long, n_tokens long, ids_crc32 long")
    return found.join(placed, "name").select("doc_id", (F.col("offset") + F.col("at")).alias("start"), "n_tokens", "ids_crc32")


def round_trip(docs: DataFrame, tokenizer_path: str, folder: str | None = None, **options) -> DataFrame:
    """Write the token files (to the shared folder by default) and read them back."""
    spark = docs.sparkSession
    folder = folder or new_path(spark, "tokens")
    files = written(write_files(docs, folder, tokenizer_path, **options), "token-files")
    if files.isEmpty():
        return spark.createDataFrame([], "doc_id long, start long, n_tokens long, ids_crc32 long")
    return read_files(files, folder)
