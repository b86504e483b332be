"""Vectorised text kernels shared by the Arrow-batch operators of this subpackage.

All of them work on the raw UTF-8 buffer of an Arrow string column, so that no Python object
is made per word.  A null text is the empty text.  Batches are cut at document boundaries into
pieces of bounded size (`slices`); one document is never cut.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U64 = np.uint64
#: bytes of text handled at once; a longer single document is handled alone
PIECE_BYTES = 1 << 20

_rng = np.random.default_rng(20240229)
_BYTE_VALUE = _rng.integers(1, 2**63, 256, dtype=np.int64).astype(U64) | U64(1)
_GRAM_VALUE = _rng.integers(1, 2**63, 64, dtype=np.int64).astype(U64) | U64(1)
_OTHER_VALUE = _rng.integers(1, 2**63, 64, dtype=np.int64).astype(U64) | U64(1)
_BASE = U64(0x9E3779B97F4A7C15)

#: separators of `[^\x20\x09-\x0D]+`
SPACE = np.zeros(256, dtype=bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
#: separators of `[^\x00-\x2F\x3A-\x60\x7B-\x7F]+`, after A-Z became a-z
PUNCT = np.zeros(256, dtype=bool)
PUNCT[[*range(0x00, 0x30), *range(0x3A, 0x61), *range(0x7B, 0x80)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[0x41:0x5B] += 0x20


def mix64(x: np.ndarray, seed: int = 0) -> np.ndarray:
    """Bijective finaliser over 64-bit values; another seed gives another order."""
    x = x ^ U64(seed * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
    x = (x ^ (x >> U64(30))) * U64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U64(27))) * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


def text_column(batch: pa.RecordBatch, name: str = "text") -> pa.Array:
    column = batch.column(batch.schema.get_field_index(name))
    if column.null_count:
        column = pc.fill_null(column, "")
    return column


def text_buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The UTF-8 bytes of all rows and their offsets (one more than rows)."""
    column = column.cast(pa.large_string())
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    if data is None or not len(column):
        return np.zeros(0, dtype=np.uint8), np.zeros(len(column) + 1, dtype=np.int64)
    return np.frombuffer(data, dtype=np.uint8)[at[0] : at[-1]], at - at[0]


def slices(batch: pa.RecordBatch, text: str = "text", limit: int = PIECE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cuts a batch between rows so that each piece has at most `limit` bytes of text, or one row."""
    if not batch.num_rows:
        return
    sizes = pc.fill_null(pc.binary_length(batch.column(batch.schema.get_field_index(text))), 0).to_numpy(zero_copy_only=False)
    first, held = 0, 0
    for i, n in enumerate(sizes.tolist()):
        if i > first and held + n > limit:
            yield batch.slice(first, i - first)
            first, held = i, 0
        held += n
    yield batch.slice(first)


@dataclass
class Words:
    """Words of some documents in order: their document, byte span, 64-bit hash; words per document."""

    doc: np.ndarray
    start: np.ndarray
    end: np.ndarray
    value: np.ndarray
    counts: np.ndarray
    first: np.ndarray  # index of each document's first word, one more at the end


def split_words(buf: np.ndarray, offsets: np.ndarray, separator: np.ndarray = SPACE, lower: bool = False, hashed: bool = True) -> Words:
    docs = len(offsets) - 1
    n = len(buf)
    if lower:
        buf = _LOWER[buf]
    gap = separator[buf]
    edge = np.zeros(n + 1, dtype=bool)
    edge[offsets[:-1]] = True
    edge[n] = True
    before = np.empty(n, dtype=bool)
    if n:
        before[0] = True
        before[1:] = gap[:-1]
    before |= edge[:n]
    after = np.empty(n, dtype=bool)
    if n:
        after[-1] = True
        after[:-1] = gap[1:]
    after |= edge[1:]
    word = ~gap
    start = np.flatnonzero(word & before)
    end = np.flatnonzero(word & after) + 1
    first = np.searchsorted(start, offsets)
    counts = np.diff(first)
    doc = np.repeat(np.arange(docs, dtype=np.int32), counts)
    value = np.zeros(len(start), dtype=U64)
    if hashed and len(start):
        lengths = np.diff(np.append(start, n))
        place = np.arange(start[0], n, dtype=np.int64)
        place -= np.repeat(start, lengths)
        powers = np.empty(int(lengths.max()), dtype=U64)
        powers[0] = 1
        powers[1:] = _BASE
        powers = np.multiply.accumulate(powers)
        terms = _BYTE_VALUE[buf[start[0] :]]
        terms *= powers[place]
        terms[gap[start[0] :]] = 0
        value = np.add.reduceat(terms, start - start[0])
        value = mix64(value + (end - start).astype(U64))
    return Words(doc, start, end, value, counts, first)


def grams(words: Words, n: int, other: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all runs of n words within one document, and the index of each run's first word; `other` gives independent ones."""
    factors = _OTHER_VALUE if other else _GRAM_VALUE
    total = len(words.value) - n + 1
    if total <= 0:
        return np.zeros(0, dtype=U64), np.zeros(0, dtype=np.int64)
    at = np.flatnonzero(words.doc[: total] == words.doc[n - 1 :])
    sums = words.value[:total] * factors[0]
    for j in range(1, n):
        sums += words.value[j : total + j] * factors[j]
    return mix64(sums[at], n), at


def code_points(buf: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Code points of each document: bytes that don't continue a UTF-8 sequence."""
    heads = np.zeros(len(buf) + 1, dtype=np.int64)
    np.cumsum((buf & 0xC0) != 0x80, out=heads[1:])
    return heads[offsets[1:]] - heads[offsets[:-1]]


def per_document(mask: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """How many set places of `mask` fall in each [offsets[i], offsets[i+1])."""
    sums = np.zeros(len(mask) + 1, dtype=np.int64)
    np.cumsum(mask, out=sums[1:])
    return sums[offsets[1:]] - sums[offsets[:-1]]
