"""Exact removal of repeated word passages by difference-cover anchors.

A window is `length` consecutive words.  A word goes if a window over it occurs earlier as well: in a
smaller doc_id, or at an earlier start of the same document.  Windows are judged on the input.

Hashing every window of the corpus is what this avoids.  With a difference cover D modulo v, two equal
windows at places i and j have some shift below v at which both i + shift and j + shift lie in D modulo
v, so they share an anchor: the length - v + 1 words from there.  The steps:

1. `packed`: texts in compressed batches, written once to reliable storage.
2. Anchors are hashed at cover places only; each batch sends each hash once to the part of the hash space
   that owns it (4 bytes each), and gets back one bit for it: whether another batch has it too.
3. Extension: only windows over shared anchors are hashed (two independent hashes of 64 bits), and each batch
   sends each such window once with its first (doc_id, start); back comes one bit: whether an earlier one exists.
4. Words under such windows, and under later windows of the same batch, are dropped.

Equal windows are told by 96 bits and more, words by 64: of 10**13 windows two different ones are taken for
equal with a chance of 10**-3.  Inside a batch 64 bits decide, on at most a few million windows.

Scale: the number of parts follows the corpus, so a part holds a few MB; a batch loops over the parts that it has
hashes in and no others.  A hot passage does not gather documents: a batch of documents sends a hash once, in
20 bytes or so, and a part is handled as Arrow columns.  What returns is bits.

Edge cases: a null or wordless text has 0 words and the empty kept text; texts shorter than a window keep
all words; equal rows with one doc_id stand at the same place, so neither is earlier and both stay; a null
doc_id counts as smaller than all others; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import settled
from .textkit import U64, grams, slices, split_words, text_buffer, text_column

#: fixed values: smallest difference covers of some periods
COVERS = {3: (0, 1), 7: (0, 1, 3), 13: (0, 1, 3, 9), 21: (0, 1, 4, 14, 16), 31: (0, 1, 3, 8, 12, 18)}
SHORTEST_ANCHOR = 8
BATCH_BYTES, PART_BYTES = 4 << 20, 8 << 20
_NONE = -(1 << 63)


def cover_for(length: int) -> tuple[int, tuple[int, ...]]:
    """The largest period that leaves anchors of at least SHORTEST_ANCHOR words; period 1 hashes every place."""
    period = max((v for v in COVERS if length - v + 1 >= SHORTEST_ANCHOR), default=1)
    return period, COVERS.get(period, (0,))


def packed(documents: DataFrame) -> DataFrame:
    """(batch, bytes, ids, ends, texts): documents in batches, ordered by doc_id inside each; checkpointed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        press = zstandard.ZstdCompressor(level=3)
        number = TaskContext.get().partitionId() << 32
        for batch in batches:
            for part in slices(batch, limit=BATCH_BYTES):
                ids = np.array([_NONE if x is None else x for x in part.column(0).to_pylist()], dtype=np.int64)
                order = np.argsort(ids, kind="stable")
                buf, offsets = text_buffer(text_column(part).take(pa.array(order)))
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array([number], pa.int64()),
                        pa.array([len(buf)], pa.int64()),
                        pa.array([press.compress(ids[order].tobytes())], pa.binary()),
                        pa.array([press.compress(offsets[1:].tobytes())], pa.binary()),
                        pa.array([press.compress(buf.tobytes())], pa.binary()),
                    ],
                    names=["batch", "bytes", "ids", "ends", "texts"],
                )
                number += 1

    return settled(documents.select("doc_id", "text").mapInArrow(run, "batch long, bytes long, ids binary, ends binary, texts binary"))


class Batch:
    """One batch of documents, its words, and the hashes that it sends."""

    def __init__(self, ids: bytes, ends: bytes, texts: bytes, length: int, bits: int):
        unpack = zstandard.ZstdDecompressor()
        self.ids = np.frombuffer(unpack.decompress(ids), dtype=np.int64)
        self.offsets = np.concatenate([[0], np.frombuffer(unpack.decompress(ends), dtype=np.int64)])
        self.text = unpack.decompress(texts)
        self.length, self.bits = length, bits
        self.words = split_words(np.frombuffer(self.text, dtype=np.uint8), self.offsets)
        period, cover = cover_for(length)
        self.anchor = length - period + 1
        values, at = grams(self.words, self.anchor)
        place = at - self.words.first[self.words.doc[at]]
        inside = np.isin(place % period, cover)
        self.anchor_at = at[inside]
        self.anchors, self.anchor_of, counts = np.unique(values[inside], return_inverse=True, return_counts=True)
        self.local = counts > 1

    def parts(self, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The parts that the sorted values fall in, and where each one's stretch begins, one more at the end."""
        of = (values >> U64(64 - self.bits)).astype(np.int64)
        first = np.flatnonzero(np.concatenate([[True], of[1:] != of[:-1]])) if len(of) else np.zeros(0, dtype=np.int64)
        return of[first], np.append(first, len(of))

    def answered(self, values: np.ndarray, answers) -> np.ndarray:
        """One flag for each sorted value, from the returned bits of its part."""
        out = np.zeros(len(values), dtype=bool)
        own, edges = self.parts(values)
        for x in answers or ():
            i = np.searchsorted(own, x["part"])
            a, b = edges[i], edges[i + 1]
            out[a:b] = np.unpackbits(np.frombuffer(x["flags"], dtype=np.uint8))[: b - a]
        return out

    def find_windows(self, shared) -> None:
        """The windows over shared anchors: where, which of the distinct ones, and where those come first."""
        words, n = self.words, self.length
        hot = (self.answered(self.anchors, shared) | self.local)[self.anchor_of]
        at = self.anchor_at[hot]
        low = np.maximum(at - (n - self.anchor), words.first[words.doc[at]]) if len(at) else at
        step = np.zeros(len(words.value) + 1, dtype=np.int32)
        np.add.at(step, low, 1)
        np.add.at(step, at + 1, -1)
        candidate = np.cumsum(step)[:-1] > 0
        values, where = grams(words, n)
        chosen = candidate[where]
        self.window_at = where[chosen]
        self.candidates = chosen
        # batches are ordered by doc_id, so the first of equal windows is the earliest one
        self.windows, self.window_first, self.window_of = np.unique(values[chosen], return_index=True, return_inverse=True)

    def places(self) -> tuple[np.ndarray, np.ndarray]:
        """(doc_id, start) of each window."""
        doc = self.words.doc[self.window_at]
        return self.ids[doc], self.window_at - self.words.first[doc]

    def removed(self, earlier) -> np.ndarray:
        """Which words go."""
        ids, starts = self.places()
        first = self.window_first[self.window_of]
        later = self.answered(self.windows, earlier)[self.window_of] | (ids != ids[first]) | (starts != starts[first])
        step = np.zeros(len(self.words.value) + 1, dtype=np.int32)
        np.add.at(step, self.window_at[later], 1)
        np.add.at(step, self.window_at[later] + self.length, -1)
        return np.cumsum(step)[:-1] > 0


def _rows(values: np.ndarray, edges: np.ndarray) -> pa.Array:
    """The bytes of each stretch of the values as a row."""
    values = np.ascontiguousarray(values)
    return pa.Array.from_buffers(pa.binary(), len(edges) - 1, [None, pa.py_buffer((edges * values.itemsize).astype(np.int32)), pa.py_buffer(values)])


def _column(part: pa.Table, name: str, kind) -> tuple[np.ndarray, np.ndarray]:
    """All rows' values of a binary column one after another, and how many each row has."""
    column = part.column(name).cast(pa.large_binary()).combine_chunks()
    chunks = column.chunks if isinstance(column, pa.ChunkedArray) else [column]
    values, sizes = [np.zeros(0, dtype=kind)], [np.zeros(0, dtype=np.int64)]
    for chunk in chunks:
        at = np.frombuffer(chunk.buffers()[1], dtype=np.int64)[chunk.offset : chunk.offset + len(chunk) + 1]
        values.append(np.frombuffer(chunk.buffers()[2], dtype=np.uint8)[at[0] : at[-1]].view(kind))
        sizes.append(np.diff(at) // np.dtype(kind).itemsize)
    return np.concatenate(values), np.concatenate(sizes)


def _of_part(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, pa.Table]]:
    """All rows of one part at a time; rows come sorted by part."""
    held: list[pa.RecordBatch] = []
    now = None
    for batch in batches:
        keys = batch.column(0).to_numpy(zero_copy_only=False)
        edges = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else []
        for a, b in zip(edges, [*edges[1:], len(keys)]):
            if held and now != keys[a]:
                yield now, pa.Table.from_batches(held)
                held = []
            now = int(keys[a])
            held.append(batch.slice(a, b - a))
    if held:
        yield now, pa.Table.from_batches(held)


_ANSWER = "batch long, part int, flags binary"


def _answers(part: int, rows: pa.Table, sizes: np.ndarray, flags: np.ndarray) -> pa.RecordBatch:
    """One row of bits for each row of the part that has a flag set."""
    ends = np.cumsum(sizes)
    sums = np.concatenate([[0], np.cumsum(flags)])
    some = np.flatnonzero(sums[ends] > sums[ends - sizes])
    told = [np.packbits(flags[ends[i] - sizes[i] : ends[i]]).tobytes() for i in some.tolist()]
    return pa.RecordBatch.from_arrays([pa.array(rows.column("batch").to_numpy()[some]), pa.array(np.full(len(some), part, dtype=np.int32)), pa.array(told, pa.binary())], names=["batch", "part", "flags"])


def _gathered(answers: DataFrame, name: str) -> DataFrame:
    return answers.groupBy("batch").agg(F.collect_list(F.struct("part", "flags")).alias(name))


def without_repeats(documents: DataFrame, length: int = 20) -> DataFrame:
    """doc_id, n_words, n_removed and the kept words, joined by single spaces, for each row of (doc_id, text)."""
    texts = packed(documents)
    total, batches = texts.agg(F.coalesce(F.sum("bytes"), F.lit(0)), F.count("*")).first()
    bits = max(6, (max(total, 1) // PART_BYTES).bit_length())

    def low_bits(values: np.ndarray) -> np.ndarray:
        return ((values << U64(bits)) >> U64(32)).astype(np.uint32)

    def send_anchors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                own = Batch(row["ids"], row["ends"], row["texts"], length, bits)
                to, edges = own.parts(own.anchors)
                columns = [pa.array(to.astype(np.int32)), pa.array(np.full(len(to), row["batch"])), _rows(low_bits(own.anchors), edges)]
                yield pa.RecordBatch.from_arrays(columns, names=["part", "batch", "hashes"])

    def meet_anchors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, rows in _of_part(batches):
            own, sizes = _column(rows, "hashes", np.uint32)
            # a value stands once in a batch, unless two anchors share their 32 bits: then both are only taken for shared
            every = np.sort(own)
            twice = np.unique(every[1:][every[1:] == every[:-1]])
            at = np.minimum(np.searchsorted(twice, own), max(len(twice) - 1, 0))
            yield _answers(part, rows, sizes, twice[at] == own if len(twice) else np.zeros(len(own), dtype=bool))

    def send_windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                own = Batch(row["ids"], row["ends"], row["texts"], length, bits)
                own.find_windows(row["shared"])
                ids, starts = (x[own.window_first] for x in own.places())
                to, edges = own.parts(own.windows)
                check = grams(own.words, length, other=True)[0][own.candidates][own.window_first]
                least = int(ids.min()) if len(ids) else 0
                columns = [pa.array(to.astype(np.int32)), *(pa.array(np.full(len(to), x, dtype=np.int64)) for x in (row["batch"], least))]
                columns += [_rows(x, edges) for x in (low_bits(own.windows), check, ids - least, starts.astype(np.int32))]
                yield pa.RecordBatch.from_arrays(columns, names=["part", "batch", "least", "hashes", "checks", "ids", "starts"])

    def meet_windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, rows in _of_part(batches):
            values, sizes = _column(rows, "hashes", np.uint32)
            checks, starts = _column(rows, "checks", U64)[0], _column(rows, "starts", np.int32)[0]
            ids = _column(rows, "ids", np.int64)[0] + np.repeat(rows.column("least").to_numpy(), sizes)
            order = np.lexsort((starts, ids, checks, values))
            new = (values[order][1:] != values[order][:-1]) | (checks[order][1:] != checks[order][:-1])
            first = order[np.maximum.accumulate(np.where(np.concatenate([[True], new]), np.arange(len(order)), 0))]
            later = np.zeros(len(values), dtype=bool)
            later[order] = (ids[order] != ids[first]) | (starts[order] != starts[first])
            yield _answers(part, rows, sizes, later)

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                own = Batch(row["ids"], row["ends"], row["texts"], length, bits)
                own.find_windows(row["shared"])
                gone = own.removed(row["earlier"])
                first = own.words.first
                lost = np.diff(np.concatenate([[0], np.cumsum(gone)])[first])
                kept = []
                for i in range(len(own.ids)):
                    words = own.text[own.offsets[i] : own.offsets[i + 1]].split()
                    if lost[i]:
                        words = [w for w, x in zip(words, gone[first[i] : first[i + 1]].tolist()) if not x]
                    kept.append(b" ".join(words))
                ids = pa.array([None if x == _NONE else x for x in own.ids.tolist()], pa.int64())
                yield pa.RecordBatch.from_arrays([ids, pa.array(own.words.counts), pa.array(lost), pa.array(kept, pa.binary()).cast(pa.string())], names=["doc_id", "n_words", "n_removed", "kept"])

    sent = texts.select("batch", "ids", "ends", "texts").mapInArrow(send_anchors, "part int, batch long, hashes binary")
    shared = _gathered(sent.repartition("part").sortWithinPartitions("part").mapInArrow(meet_anchors, _ANSWER), "shared")
    shared = settled(shared, batches)
    with_shared = texts.select("batch", "ids", "ends", "texts").join(shared, "batch", "left")
    windows = with_shared.mapInArrow(send_windows, "part int, batch long, least long, hashes binary, checks binary, ids binary, starts binary")
    earlier = _gathered(windows.repartition("part").sortWithinPartitions("part").mapInArrow(meet_windows, _ANSWER), "earlier")
    both = with_shared.join(earlier, "batch", "left")
    return both.mapInArrow(finish, "doc_id long, n_words long, n_removed long, kept string")
