"""Token counts of whole texts, long documents in overlapping pieces that are spliced where both agree.

A document over `piece` code points is encoded in overlapping pieces with offsets.  Two neighbouring
pieces are spliced at a stable common boundary: a place inside their overlap where a non-space is
followed by U+0020 and where both encodings start a token.  The byte-level pre-tokenizer never keeps
such a space with what stands before it, so the tokens before the place (from the left piece) and after
it (from the right piece) are those of the whole text; special strings hold no space, so none is cut.
Where an overlap has no such place it is widened, twice as far each time, in the end to the next piece's
end, which is then swallowed.

Edge cases: a null text is empty (0 bytes, 0 tokens); other columns are ignored; repeated rows give
repeated results; an empty table gives no rows; a long text without spaces is encoded as a whole.
"""

from __future__ import annotations

import os
import re
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from .textkit import slices, text_column

PIECE, OVERLAP = 1 << 15, 1 << 9
_STABLE = re.compile(r"(?<=\S) ")
_LOADED: dict[str, object] = {}


def vocabulary_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def tokenizer(path: str):
    """The library's tokenizer for a file, once per process and single-threaded."""
    if path not in _LOADED:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        _LOADED[path] = Tokenizer.from_file(path)
    return _LOADED[path]


def _starts(encoding) -> tuple[list[int], list[int]]:
    return [a for a, _ in encoding.offsets], [b for _, b in encoding.offsets]


def _splice_point(text: str, low: int, high: int, left, left_at: int, right, right_at: int) -> int | None:
    """The first stable place in [low, high) that no token of either encoding crosses."""
    left_starts, left_ends = left
    right_starts, right_ends = right
    for found in _STABLE.finditer(text, low + 1, high):
        p = found.start()
        crossed = any(a + left_at < p < b + left_at for a, b in zip(left_starts[-4 * OVERLAP :], left_ends[-4 * OVERLAP :]))
        if not crossed and not any(a + right_at < p < b + right_at for a, b in zip(right_starts[: 4 * OVERLAP], right_ends[: 4 * OVERLAP])):
            return p
    return None


def count_long(encode, text: str, piece: int = PIECE, overlap: int = OVERLAP) -> int:
    """Tokens of one long text; `encode` maps a list of strings to encodings with offsets."""
    n = len(text)
    begins = list(range(0, n, piece))
    ends = [min(n, b + piece + overlap) for b in begins]
    encoded = [_starts(e) for e in encode([text[a:b] for a, b in zip(begins, ends)])]
    total, from_here, i = 0, 0, 0
    while i < len(begins):
        j = i + 1
        width = overlap
        place = None
        while j < len(begins) and ends[i] < n:
            if ends[j] <= ends[i]:
                j += 1
                continue
            place = _splice_point(text, begins[j], ends[i], encoded[i], begins[i], encoded[j], begins[j])
            if place is not None:
                break
            width *= 2
            ends[i] = min(n, max(ends[i], begins[i] + piece) + width)
            encoded[i] = _starts(encode([text[begins[i] : ends[i]]])[0])
        until = n if place is None else place
        total += sum(1 for a in encoded[i][0] if from_here <= a + begins[i] < until)
        if place is None:
            break
        from_here, i = place, j
    return total


def count_tokens(documents: DataFrame, path: str, limit: int = 1024, piece: int = PIECE, overlap: int = OVERLAP) -> DataFrame:
    """doc_id, n_bytes, n_tokens and whether that is over `limit`, for each row of (doc_id, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = tokenizer(path)
        fast = getattr(own, "encode_batch_fast", own.encode_batch)
        for batch in batches:
            for part in slices(batch, limit=1 << 20):
                column = text_column(part)
                texts = column.to_pylist()
                short = [i for i, t in enumerate(texts) if len(t) <= piece]
                counts = [0] * len(texts)
                for i, e in zip(short, fast([texts[i] for i in short], add_special_tokens=False)):
                    counts[i] = len(e)
                for i, t in enumerate(texts):
                    if len(t) > piece:
                        counts[i] = count_long(lambda x: own.encode_batch(x, add_special_tokens=False), t, piece, overlap)
                n_tokens = pa.array(counts, pa.int64())
                yield pa.RecordBatch.from_arrays(
                    [part.column(0).cast(pa.int64()), pc.binary_length(column).cast(pa.int64()), n_tokens, pc.greater(n_tokens, limit)],
                    names=["doc_id", "n_bytes", "n_tokens", "over_limit"],
                )

    return documents.select("doc_id", "text").mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
