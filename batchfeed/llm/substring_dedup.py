"""Substring dedup by level-wise doubling.

A passage of words is repeated only if its parts are, so windows are judged level by
level: only what repeats at one length is looked at for twice the length, and levels
stop when nothing survives. They start at single words, every one of which is asked
about, and go up by doubling to the wanted window (1, 2, 4, 7, 13 for 13: a length is
half the next one, rounded up, so the two halves may overlap), then, up to `longest`
words (None: without end), to 2, 4, 8 ... times the window. Texts are cut into words
once; from then on a block carries a `State` of the windows that are left.

Levels ask the corpus through `key_exchange`, so a window costs one entry per block of
documents and no window, however common, makes a hot group. Windows of the wanted
length and up are compared by 128 bits, two chains over their words' 64-bit hashes: the
first is the key, the second travels with it and parts windows that share a key by
chance. 10^13 windows are 5 * 10^25 pairs, so some share a key, but two that differ
share all 128 bits with a chance of about 10^-13. Windows shorter than the wanted one only
choose candidates, for which 64 bits do.

Edge cases: null and empty texts have no words; a null doc_id counts as the largest
id, so that it yields to all others; rows of one doc_id do not remove each other's
words; texts shorter than a window are kept whole; other columns are not read.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, functions as F

from .common import mixed, new_path, remove, written
from .key_exchange import ASK_SCHEMA, Block, Exchange, answered, ask_rows, block_rows, blocks, cut, joined, packed, unpacked, values_in_order

STATE_SCHEMA = "block long, crc long, candidates long, payload binary"

_LAST = np.int64((1 << 63) - 1)
_SECOND = np.uint64(0xC2B2AE3D27D4EB4F)


def spaced_words(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """All words, one after the other with a space behind each: their bytes, the bytes of each word, the words of each text."""
    raw = np.frombuffer(b" ".join([*texts, b""]), np.uint8)
    space = (raw == 32) | (raw - np.uint8(9) < 5)
    ends = np.flatnonzero(space)
    lengths = np.diff(ends, prepend=-1)
    ends, lengths = ends[lengths > 1], lengths[lengths > 1]
    space[ends] = False
    body = raw[~space]
    body[np.cumsum(lengths) - 1] = 32
    sizes = np.diff(np.searchsorted(ends, np.cumsum([len(t) + 1 for t in texts])), prepend=0)
    return body, lengths, sizes.astype(np.int64)


@dataclass
class State:
    """What a block carries from level to level: its documents, the windows asked about next, and what was found.

    Windows are hashed anew from the block's words, given as numbers in its vocabulary, as
    long as these take less room than two hashes for each window; then windows of the
    wanted length and up bring their hashes, and the words are dropped.
    """

    sizes: np.ndarray
    ids: np.ndarray
    vocabulary: np.ndarray
    numbers: np.ndarray
    at: np.ndarray
    first: np.ndarray
    second: np.ndarray
    gone: np.ndarray
    most: np.ndarray

    @classmethod
    def of(cls, block: Block) -> State:
        """A block's words, each of them a window to be asked about."""
        body, lengths, sizes = spaced_words(block.texts)
        n, offsets = len(lengths), np.append(0, np.cumsum(lengths))
        found = pa.LargeBinaryArray.from_buffers(pa.large_binary(), n, [None, pa.py_buffer(offsets), pa.py_buffer(body)]).dictionary_encode()
        vocabulary = np.fromiter(map(xxhash.xxh64_intdigest, found.dictionary.to_numpy(zero_copy_only=False)), np.uint64, len(found.dictionary))
        numbers = found.indices.to_numpy().astype(np.uint16 if len(vocabulary) < 1 << 16 else np.uint32)
        none = np.zeros(0, np.uint64)
        return cls(sizes, np.where(block.doc_null, _LAST, block.doc_ids), vocabulary, numbers, np.arange(n), none, none, np.zeros(n, bool), np.zeros(len(sizes), np.int64))

    @classmethod
    def loaded(cls, data: bytes) -> State:
        sizes, ids, vocabulary, numbers, at, first, second, gone, most = (unpacked(x) for x in cut(data))
        return cls(sizes, ids, vocabulary, numbers, np.cumsum(at, dtype=np.int64), first, second, np.unpackbits(gone, count=int(sizes.sum())).astype(bool), most)

    def dumped(self) -> bytes:
        at = np.diff(self.at, prepend=0).astype(np.uint32)
        return joined([packed(x) for x in (self.sizes, self.ids, self.vocabulary, self.numbers, at, self.first, self.second, np.packbits(self.gone), self.most)])

    @property
    def doc(self) -> np.ndarray:
        """The document of every position."""
        return np.repeat(np.arange(len(self.sizes)), self.sizes)

    def hashes(self, ladder: list[int], length: int, lane: int = 0) -> np.ndarray:
        """Hash of the window of length at every position, made by way of the ladder's lengths; lane 1: another hash."""
        out = self.vocabulary[self.numbers]
        if lane:
            out = mixed(out, _SECOND)
        for a, b in zip(ladder, ladder[1:]):
            if b <= length and len(out):
                step = b - a
                out = np.append(mixed(out[:-step], out[step:]), np.zeros(min(step, len(out)), np.uint64))
        return out

    def climb(self, ladder: list[int], level: int, window: int, again: np.ndarray) -> None:
        """From the windows of a level, those of `at` repeated where `again` says so, to the candidates of the next one.

        A window is a candidate if its first and its last words, as many as the level has, both repeat.
        """
        ends, doc = np.cumsum(self.sizes), self.doc
        if level + 1 == len(ladder):
            self.at, self.first, self.second, self.vocabulary, self.numbers = (x[:0] for x in (self.at, self.first, self.second, self.vocabulary, self.numbers))
        else:
            length, longer = ladder[level], ladder[level + 1]
            step = longer - length
            where = np.full(len(doc), -1, np.int64)
            where[self.at[again]] = np.flatnonzero(again)
            at = self.at[again]
            at = at[at + longer <= ends[doc[at]]]
            at = at[where[at + step] >= 0]
            if not len(self.numbers):
                here, there = where[at], where[at + step]
                self.first, self.second = mixed(self.first[here], self.first[there]), mixed(self.second[here], self.second[there])
            elif longer >= window and 16 * len(at) < self.vocabulary.nbytes + self.numbers.nbytes:
                self.first, self.second = (self.hashes(ladder, longer, lane)[at] for lane in (0, 1))
                self.vocabulary, self.numbers = self.vocabulary[:0], self.numbers[:0]
            self.at = at


def _ordered(hashes: np.ndarray, second: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Places of the hashes in ascending order, equal ones as they come, and where in it each distinct hash begins.

    With second hashes the keys of equal first ones are as many as they have second ones.
    Numbers are sorted far faster than their places, so the places stand in the lowest bits.
    """
    n = len(hashes)
    low = np.uint64((1 << max(n - 1, 0).bit_length()) - 1)
    order = hashes & ~low
    order |= np.arange(n, dtype=np.uint64)
    order.sort()
    order &= low
    order = order.view(np.int64)
    ascending = hashes[order]
    if (ascending[1:] < ascending[:-1]).any():  # some differ in the lowest bits alone
        order = order[np.argsort(ascending, kind="stable")]
        ascending = hashes[order]
    new = np.ones(n, bool)
    np.not_equal(ascending[1:], ascending[:-1], out=new[1:])
    if second is not None:
        other = second[order]
        if ((other[1:] != other[:-1]) & ~new[1:]).any():
            order = np.lexsort((second, hashes))
            ascending, other = hashes[order], second[order]
            new[1:] = (ascending[1:] != ascending[:-1]) | (other[1:] != other[:-1])
    return order, np.flatnonzero(new)


def _in_place(order: np.ndarray, starts: np.ndarray, values: np.ndarray) -> np.ndarray:
    """What each distinct hash has, for every hash."""
    out = np.empty(len(order), values.dtype)
    out[order] = np.repeat(values, np.diff(starts, append=len(order)))
    return out


def _distinct(hashes: np.ndarray, second: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ascending distinct keys, the place of each hash among them, and an entry of each."""
    order, starts = _ordered(hashes, second)
    return hashes[order[starts]], _in_place(order, starts, np.arange(len(starts))), order[starts]


def _sides(state: State, ladder: list[int], length: int, window: int) -> tuple[np.ndarray, np.ndarray | None]:
    """First and second hashes of the windows asked about; those shorter than the wanted one have no second."""
    if not len(state.numbers):
        return state.first, state.second
    return state.hashes(ladder, length)[state.at], state.hashes(ladder, length, 1)[state.at] if length >= window else None


def _ends_of(order: np.ndarray, starts: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Least and largest id of each distinct hash."""
    if not len(starts):
        return ids[:0], ids[:0]
    ids = ids[order]
    return np.minimum.reduceat(ids, starts), np.maximum.reduceat(ids, starts)


def _repeated_short(keys, place, values):
    """Short windows with two documents at least: several in a block, or entries of several blocks."""
    several = np.bincount(place, minlength=len(keys)) > 1
    np.logical_or.at(several, place, values[0] > 0)
    return [several[place].astype(np.uint8)], []


def _repeated_long(keys, place, values):
    """1 if a document of another id has the window, plus 2 if one with a smaller id than the block's least."""
    one = np.empty(len(keys), np.uint64)
    one[place] = values[2]
    if (one[place] != values[2]).any():
        keys, place, _ = _distinct(keys[place], values[2])
    low = np.full(len(keys), _LAST)
    np.minimum.at(low, place, values[0])
    several = np.zeros(len(keys), bool)
    np.logical_or.at(several, place, (values[1] > 0) | (values[0] > low[place]))
    flag = several[place] + 2 * (low[place] < values[0])
    return [flag.astype(np.uint8)], [np.array([several.sum()], np.int64)]


def _ladder(window: int, longest: int | None) -> list[int]:
    """The lengths that are looked at, from one word on; without a longest, all that a text of 2**31 words could have."""
    out = [window]
    while out[0] > 1:
        out.insert(0, -(-out[0] // 2))
    while out[-1] * 2 <= (1 << 31 if longest is None else longest):
        out.append(out[-1] * 2)
    return out


def _asked(state: State, ladder: list[int], level: int, window: int):
    """What a block asks at a level: order and starts of its windows, their keys and values.

    Windows shorter than the wanted one bring whether several documents have them, others
    the least doc_id, whether they have several, and the second hash.
    """
    length = ladder[level]
    hashes, second = _sides(state, ladder, length, window)
    order, starts = _ordered(hashes, second)
    first, doc = order[starts], state.doc[state.at]
    if length < window:  # places ascend among equal windows, and so do their documents
        last = order[np.append(starts[1:], len(order)) - 1] if len(starts) else first
        values = [(doc[first] < doc[last]).astype(np.uint8)]
    else:
        low, high = _ends_of(order, starts, state.ids[doc])
        values = [low, (low < high).astype(np.uint8), second[first]]
    return order, starts, hashes[first], values


def _asks(state: State, ladder: list[int], level: int, window: int):
    """Keys, the place of each window among them, and values."""
    order, starts, keys, values = _asked(state, ladder, level, window)
    return keys, _in_place(order, starts, np.arange(len(keys))), values


def _judge(state: State, ladder: list[int], level: int, window: int, answers: list[np.ndarray]) -> None:
    """Take in the answers of a level and go on to the next."""
    length = ladder[level]
    order, starts, _, values = _asked(state, ladder, level, window)
    got = _in_place(order, starts, answers[0]) if len(order) else np.zeros(0, np.uint8)
    again = (got & 1) > 0
    if length >= window:
        docs = state.doc[state.at]
        state.most = np.where(np.bincount(docs[again], minlength=len(state.most)) > 0, length, state.most)
        if length == window:
            smaller = np.zeros(len(state.gone), bool)
            smaller[state.at[((got & 2) > 0) | (again & (state.ids[docs] > _in_place(order, starts, values[0])))]] = True
            state.gone = spread(smaller, window)
    state.climb(ladder, level, window, again)


def spread(starts: np.ndarray, length: int) -> np.ndarray:
    """Words covered by windows of length that start at the marked positions."""
    edge = np.zeros(len(starts) + length + 1, np.int64)
    at = np.flatnonzero(starts)
    np.add.at(edge, at, 1)
    np.add.at(edge, at + length, -1)
    return np.cumsum(edge)[: len(starts)] > 0


def _states(rows: list[tuple[int, int, State]]) -> pa.RecordBatch:
    block, crc, states = zip(*rows, strict=True)
    return pa.RecordBatch.from_arrays([pa.array(block, pa.int64()), pa.array(crc, pa.int64()), pa.array([len(s.at) for s in states], pa.int64()), pa.array([s.dumped() for s in states], pa.binary())], ["block", "crc", "candidates", "payload"])


def _asker(ladder: list[int], level: int, window: int, parts: int):
    """What every block asks at a level."""

    def ask(rows):
        for batch in rows:
            for row in batch.to_pylist():
                _, _, keys, values = _asked(State.loaded(row["payload"]), ladder, level, window)
                yield ask_rows(row["block"], row["crc"], keys, values, parts)

    return ask


def _judger(ladder: list[int], level: int, window: int):
    """A block's state after the answers of a level."""

    def judge(left: pa.Table, right: pa.Table) -> pa.Table:
        out = []
        for row in left.to_pylist():
            state = State.loaded(row["payload"])
            _judge(state, ladder, level, window, values_in_order(right.to_pylist(), row["crc"]))
            out.append((row["block"], row["crc"], state))
        if not out:
            raise ValueError("answers to a block that is not there")
        return pa.Table.from_batches([_states(out)])

    return judge


def remove_repeats(docs: DataFrame, window: int = 13, longest: int | None = 0, keep_text: bool = False, block_bytes: int = 5 << 20, part_bytes: int = 10 << 20, fan: int = 4096) -> DataFrame:
    """Per row of docs(doc_id, text): n_words, n_removed, kept_sha256, longest_repeat, spans (and kept_text).

    A word is removed if a window over it also starts in a document with a smaller
    doc_id. longest_repeat: the longest level from `window` on, up to `longest`, at which
    the document shares a window with another; spans: the removed word ranges.
    """
    spark, ladder = docs.sparkSession, _ladder(window, longest)
    packed_docs = blocks(docs, block_bytes)
    exchange = Exchange.over(packed_docs, part_bytes, fan)

    def start(rows):
        for batch in rows:
            for block in block_rows(batch):
                yield _states([(block.number, block.crc, State.of(block))])

    at = new_path(spark, "state")
    states = written(packed_docs.mapInArrow(start, STATE_SCHEMA), "state", at)
    for level, length in enumerate(ladder):
        before, asked_at, at = at, new_path(spark, "level"), new_path(spark, "state")
        answers = written(answered(states.mapInArrow(_asker(ladder, level, window, exchange.first), ASK_SCHEMA), exchange, _repeated_long if length >= window else _repeated_short), "level", asked_at)
        exchange.release(spark)
        states = written(states.groupBy("block").cogroup(answers.where("block >= 0").groupBy("block")).applyInArrow(_judger(ladder, level, window), STATE_SCHEMA), "state", at)
        remove(spark, before, asked_at)
        exchange.release(spark)
        if not states.agg(F.sum("candidates")).first()[0]:
            break

    schema = "doc_id long, n_words long, n_removed long, kept_sha256 string, longest_repeat long, spans array<struct<first:long,end:long>>, kept_text string"

    def finish(left: pa.Table, right: pa.Table) -> pa.Table:
        (block,) = block_rows(left)
        (row,) = right.to_pylist()
        if row["crc"] != block.crc:
            raise ValueError("state of another block")
        state = State.loaded(row["payload"])
        body, lengths, sizes = spaced_words(block.texts)
        if state.gone.any():
            body = body[np.repeat(~state.gone, lengths)]
        ends = np.append(0, np.cumsum(np.where(state.gone, 0, lengths)))
        rows, at, body = [], 0, body.tobytes()
        for n in sizes.tolist():
            cut_out = state.gone[at : at + n]
            edge = np.flatnonzero(np.diff(np.concatenate([[0], cut_out.view(np.int8), [0]]))).reshape(-1, 2) if cut_out.any() else np.zeros((0, 2), np.int64)
            kept = body[ends[at] : max(ends[at], ends[at + n] - 1)]
            rows.append((n, int(cut_out.sum()), hashlib.sha256(kept).hexdigest(), [{"first": a, "end": z} for a, z in edge.tolist()], kept.decode() if keep_text else None))
            at += n
        n_words, n_removed, digests, spans, kept = zip(*rows, strict=True)
        span = pa.list_(pa.struct([("first", pa.int64()), ("end", pa.int64())]))
        return pa.table({
            "doc_id": pa.array(block.doc_ids.tolist(), pa.int64(), mask=block.doc_null.astype(bool)), "n_words": pa.array(n_words, pa.int64()), "n_removed": pa.array(n_removed, pa.int64()), "kept_sha256": pa.array(digests, pa.string()),
            "longest_repeat": pa.array(state.most, pa.int64()), "spans": pa.array(spans, span), "kept_text": pa.array(kept, pa.string()),
        })

    out = packed_docs.groupBy("block").cogroup(states.groupBy("block")).applyInArrow(finish, schema)
    return out if keep_text else out.drop("kept_text")


def digest(found: DataFrame) -> DataFrame:
    return found.select("doc_id", "n_words", "n_removed", "kept_sha256")
