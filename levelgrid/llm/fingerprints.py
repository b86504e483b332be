"""Document fingerprints from terms of middling document frequency, under randomised lexicons.

The lexicon keeps the terms whose normalised inverse document frequency, ln(N / df) / ln(N), lies in a
band.  Document frequencies are counted over all documents, in a table of SLOTS places that terms share
by hash, so that neither the count nor the lexicon (one bit a place, 256 KiB) grows with the corpus.
A fingerprint holds a hash of a text's distinct lexicon terms and one shorter hash for each of the
randomised lexicons, which keep a fixed random share of the terms, from all of them to one in 2048.
Dense lexicons tell small differences, sparse ones survive large edits; the likeness of two fingerprints
is the share of lexicons, of those in which either has a term, whose hashes agree, sparse ones weighing more.

Edge cases: a null text is empty; a text with fewer than MIN_TERMS lexicon terms is hashed over all its
terms instead; texts without any term share the fingerprint of no terms and are alike (1.0) to each other
and unlike (0.0) to all others; equal texts always have equal fingerprints; repeated rows stand side by
side in the order of (doc_id, text); a null doc_id comes last in descending order; a table of one row is
its own next document; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import parts
from .textkit import PUNCT, U64, mix64, slices, split_words, text_buffer, text_column

SLOTS, BLOCK = 1 << 21, 1 << 15
BAND = (0.25, 0.75)
MIN_TERMS = 3
#: bytes of text in a range of documents; ranges are larger only beyond MOST_RANGES of them
RANGE_BYTES, MOST_RANGES = 32 << 20, 20_000
#: each randomised lexicon keeps one term in 2**d
THINNING = (0, *(d for d in range(2, 12) for _ in range(4)))
_WEIGHT = np.sqrt(2.0 ** np.array(THINNING))
_NONE = -(1 << 63)


@dataclass
class Lexicon:
    bits: np.ndarray
    documents: int
    #: of all texts
    bytes: int = 0

    def __post_init__(self):
        self.mask = np.unpackbits(self.bits).astype(bool)


def document_frequencies(documents: DataFrame) -> DataFrame:
    """(block, docs, counts): sums over all documents, BLOCK places a row.  A task sends each block once."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, docs = np.zeros(SLOTS, dtype=np.int32), 0
        for batch in batches:
            docs += batch.num_rows
            for part in slices(batch):
                words = split_words(*text_buffer(text_column(part)), PUNCT, lower=True)
                seen = np.unique((words.doc.astype(U64) << U64(32)) | (words.value % U64(SLOTS)))
                sums += np.bincount((seen & U64(0xFFFFFFFF)).astype(np.int64), minlength=SLOTS).astype(np.int32)
        pack = zstandard.ZstdCompressor(level=1)
        blocks = [i for i in range(SLOTS // BLOCK) if sums[i * BLOCK : (i + 1) * BLOCK].any()] if docs else []
        yield pa.RecordBatch.from_arrays(
            [pa.array(blocks, pa.int32()), pa.array([pack.compress(sums[i * BLOCK : (i + 1) * BLOCK].tobytes()) for i in blocks], pa.binary())], names=["block", "counts"]
        )

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        unpack = zstandard.ZstdDecompressor()
        for batch in batches:
            for block, counts in zip(batch.column(0).to_pylist(), batch.column(1)):
                own = np.frombuffer(unpack.decompress(counts.as_py()), dtype=np.int32)
                sums[block] = sums.get(block, 0) + own.astype(np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), pa.array([x.tobytes() for x in sums.values()], pa.binary())], names=["block", "counts"])

    schema = "block int, counts binary"
    return documents.select("text").mapInArrow(count, schema).repartition("block").mapInArrow(add, schema)


def lexicon(documents: DataFrame, band: tuple[float, float] = BAND) -> Lexicon:
    """What reaches the driver is one bit for each place, whatever the corpus."""
    n, size = documents.agg(F.count("*"), F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()
    scale = np.log(max(n, 2))

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            bits = []
            for counts in batch.column(1):
                df = np.frombuffer(counts.as_py(), dtype=np.int64)
                idf = np.log(max(n, 1) / np.maximum(df, 1)) / scale
                bits.append(np.packbits((df > 0) & (idf >= band[0]) & (idf <= band[1])).tobytes())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(bits, pa.binary())], names=["block", "bits"])

    bits = np.zeros(SLOTS // 8, dtype=np.uint8)
    for block, own in document_frequencies(documents).mapInArrow(judge, "block int, bits binary").collect():
        bits[block * BLOCK // 8 : (block + 1) * BLOCK // 8] = np.frombuffer(bytes(own), dtype=np.uint8)
    return Lexicon(bits, n, size)


def fingerprint_values(column: pa.Array, known: Lexicon) -> tuple[np.ndarray, np.ndarray]:
    """For each text, the 64-bit hash of its terms and its 16-bit hashes, one a lexicon; 0 is no term."""
    buf, offsets = text_buffer(column)
    docs = len(offsets) - 1
    words = split_words(buf, offsets, PUNCT, lower=True)
    inside = known.mask[(words.value % U64(SLOTS)).astype(np.int64)]
    keys = np.unique((words.doc.astype(U64) << U64(44)) | (words.value >> U64(20)))
    # distinct terms in sorted order; whether a term is in the lexicon follows from its first occurrence
    order = np.unique((words.doc[inside].astype(U64) << U64(44)) | (words.value[inside] >> U64(20)))
    held = np.bincount((order >> U64(44)).astype(np.int64), minlength=docs)
    few = held < MIN_TERMS
    if few.any():
        owner = (keys >> U64(44)).astype(np.int64)
        keep = (order >> U64(44)).astype(np.int64)
        order = np.sort(np.concatenate([order[~few[keep]], keys[few[owner]]]))
    owner = (order >> U64(44)).astype(np.int64)
    terms = order & U64((1 << 44) - 1)
    first = np.searchsorted(owner, np.arange(docs + 1))

    def fold(values: np.ndarray) -> np.ndarray:
        sums = np.zeros(len(values) + 1, dtype=U64)
        np.cumsum(values, out=sums[1:])
        return sums[first[1:]] - sums[first[:-1]]

    whole = mix64(fold(mix64(terms, 1)) + np.diff(first).astype(U64), 2)
    short = np.zeros((docs, len(THINNING)), dtype=np.uint16)
    for i, d in enumerate(THINNING):
        drawn = mix64(terms, 100 + i)
        kept = (drawn >> U64(40)) % U64(1 << d) == 0
        some = np.diff(np.concatenate([[0], np.cumsum(kept)])[first]) > 0
        value = mix64(fold(np.where(kept, mix64(drawn, 3), U64(0))), 200 + i) >> U64(48)
        short[:, i] = np.where(some, np.maximum(value, U64(1)), U64(0)).astype(np.uint16)
    return whole, short


def likeness(a: np.ndarray, b: np.ndarray, whole_a: np.ndarray, whole_b: np.ndarray) -> np.ndarray:
    either = (a > 0) | (b > 0)
    shared = either @ _WEIGHT
    return np.where(shared > 0, (((a == b) & either) @ _WEIGHT) / np.where(shared > 0, shared, 1), (whole_a == whole_b).astype(float))


def as_text(whole: np.ndarray, short: np.ndarray) -> list[str]:
    return [f"{w:016x}{s.astype('>u2').tobytes().hex()}" for w, s in zip(whole.tolist(), short)]


def fingerprints(documents: DataFrame, known: Lexicon) -> DataFrame:
    """(doc_id, fingerprint) of each row of (doc_id, text); no shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch):
                yield pa.RecordBatch.from_arrays([part.column(0).cast(pa.int64()), pa.array(as_text(*fingerprint_values(text_column(part), known)))], names=["doc_id", "fingerprint"])

    return documents.select("doc_id", "text").mapInArrow(run, "doc_id long, fingerprint string")


def _ranges(documents: DataFrame, pieces: int) -> list[int]:
    """Ids, descending: range i holds the ids from bounds[i] down to above bounds[i + 1]; each bound is an id that occurs."""
    fractions = [i / pieces for i in range(1, pieces)] or [0.5]
    row = documents.agg(F.max("doc_id").alias("most"), F.percentile_approx("doc_id", fractions, max(10_000, 10 * pieces)).alias("bounds")).first()
    return sorted({*(row["bounds"] or ()), *([] if row["most"] is None else [row["most"]])}, reverse=True) or [_NONE]


OUT = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def edited_fingerprints(documents: DataFrame, known: Lexicon) -> DataFrame:
    """Fingerprints of each text and of its edited text, whose last third is the start of the next document's.

    The next document is the one before in descending doc_id, after the last one the first.  Texts move
    once, compressed, to ranges of doc_id, a task each, whose number follows the size of all texts; the first
    document of each range is also sent to the range before it, so no range waits for another.
    """
    bounds = _ranges(documents, min(MOST_RANGES, max(parts(documents), known.bytes // RANGE_BYTES)))
    last = len(bounds) - 1
    rising = np.array(bounds[::-1], dtype=np.int64)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pack = zstandard.ZstdCompressor(level=1)
        for batch in batches:
            for part in slices(batch):
                ids = part.column(0).cast(pa.int64()).to_numpy(zero_copy_only=False) if not part.column(0).null_count else np.array([_NONE if x is None else x for x in part.column(0).to_pylist()], dtype=np.int64)
                texts = text_column(part).cast(pa.large_binary()).to_pylist()
                home = np.clip(last - np.searchsorted(rising, ids, side="left"), 0, last)
                rows = []
                for i, text in enumerate(texts):
                    own, to, packed = int(ids[i]), int(home[i]), pack.compress(text)
                    order = hashlib.md5(text).digest()
                    rows.append((to, 0, own, order, packed))
                    if own == bounds[to]:
                        rows.append((to - 1 if to else last, 1, own, order, packed))
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows), (pa.int32(), pa.int32(), pa.int64(), pa.binary(), pa.binary()))], names=["home", "beyond", "id", "tie", "packed"])

    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, str, str]]:
        """(id, text, next text) of each document, ranges and ids in order."""
        unpack = zstandard.ZstdDecompressor()
        held = None
        for batch in batches:
            for home, beyond, own, packed in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist(), batch.column(4)):
                if held is None and beyond:
                    continue  # only the first of the rows from beyond is the next document
                text = unpack.decompress(packed.as_py()).decode()
                if held is not None:
                    yield *held, text
                held = None if beyond else (own, text)
        assert held is None, "a range has no next document"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, size = [], 0
        for row in pairs(batches):
            rows.append(row)
            size += len(row[1])
            if size > 1 << 20:
                yield finish(rows)
                rows, size = [], 0
        if rows:
            yield finish(rows)

    def finish(rows: list[tuple[int, str, str]]) -> pa.RecordBatch:
        edited = []
        for _, text, following in rows:
            cut = len(text) // 3
            edited.append(text[: len(text) - cut] + following[:cut])
        texts = [r[1] for r in rows]
        column = pa.array([*texts, rows[-1][2], *edited], pa.large_string())
        whole, short = fingerprint_values(column, known)
        n = len(rows)
        names = as_text(whole, short)
        own, following, changed = slice(0, n), slice(1, n + 1), slice(n + 1, 2 * n + 1)
        return pa.RecordBatch.from_arrays(
            [
                pa.array([None if r[0] == _NONE else r[0] for r in rows], pa.int64()),
                pa.array([len(t) for t in texts], pa.int64()),
                pa.array([hashlib.sha256(t.encode()).hexdigest() for t in edited]),
                pa.array(names[own]),
                pa.array(names[changed]),
                pa.array(likeness(short[own], short[changed], whole[own], whole[changed]), pa.float64()),
                # in a piece of the run each text's next one stands behind it, but where a range ends
                pa.array(_near_next(rows, whole, short, known), pa.float64()),
            ],
            names=["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"],
        )

    dealt = documents.select("doc_id", "text").mapInArrow(deal, "home int, beyond int, id long, tie binary, packed binary")
    dealt = dealt.repartitionById(last + 1, "home").sortWithinPartitions("home", "beyond", F.desc("id"), "tie")
    return dealt.mapInArrow(run, OUT)


def _near_next(rows: list[tuple[int, str, str]], whole: np.ndarray, short: np.ndarray, known: Lexicon) -> np.ndarray:
    n = len(rows)
    out = likeness(short[:n], short[1 : n + 1], whole[:n], whole[1 : n + 1])
    ends = [i for i in range(n - 1) if rows[i][2] is not rows[i + 1][1]]
    if ends:
        own_whole, own_short = fingerprint_values(pa.array([rows[i][2] for i in ends], pa.large_string()), known)
        out[ends] = likeness(short[ends], own_short, whole[ends], own_whole)
    return out
