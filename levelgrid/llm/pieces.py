"""SentencePiece encoding and decoding by a shared-prefix forward search over distinct marked words.

A text is marked as the library does (a leading mark, U+2581 for each space) and cut into words where no
piece of the vocabulary crosses.  The distinct words of a batch are sorted, which is the order of a
depth-first walk through their trie; a stack holds the forward state of every prefix of the current
word, and a word only adds the states past the prefix it shares with the one before.

The given model is of the merge (BPE) kind, where a best-sum Viterbi search gives other results than the
library.  The forward state that is right for it is the last piece of the prefix's encoding: a piece may
follow another exactly if the two, joined, are encoded as these two, and of the pieces that end at a
place exactly one follows the encoding before it.  So the search keeps one state a prefix, as Viterbi
does, and pair checks, remembered, take the place of score sums.  Pieces that no merge reaches are left
out.  Characters outside the vocabulary become byte pieces and join with nothing.

Edge cases: a null or empty text has no ids and decodes to the empty text; U+2581 in a text is encoded as
a space is, so it decodes to a space, as in the library; very long words are searched in linear time;
other columns are kept by `encode_documents`; repeated rows give repeated results; an empty table gives
no rows.
"""

from __future__ import annotations

import re
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .textkit import slices, text_column

MARK = "▁"
#: distinct words that one process remembers between batches; beyond it starts anew
REMEMBERED = 250_000
_LETTERS = "0-9A-Za-zÀ-ÖØ-öø-ɏ"


class PieceCoder:
    """One model: its pieces, and the encodings of the words met so far."""

    def __init__(self, path: str):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        size = model.vocab_size()
        self.texts = [model.id_to_piece(i) for i in range(size)]
        plain = [i for i in range(size) if not (model.is_byte(i) or model.is_control(i) or model.is_unknown(i) or model.is_unused(i))]
        self.ids = {self.texts[i]: i for i in plain}
        self.rank = {self.texts[i]: -model.get_score(i) for i in plain}
        self.bytes = {int(self.texts[i][1:-1], 16): i for i in range(size) if model.is_byte(i)}
        self.spelled = [b"" if model.is_control(i) else self.texts[i].replace(MARK, " ").encode() for i in range(size)]
        for b, i in self.bytes.items():
            self.spelled[i] = bytes([b])
        self.reach: dict[str, int] = {}
        self.reached: dict[str, int] = {}
        for text, i in self.ids.items():
            if len(text) == 1 or self.merged(text) == [text]:
                self.reached[text] = i
                self.reach[text[-1]] = max(self.reach.get(text[-1], 0), len(text))
        self.pairs: dict[int, bool] = {}
        self.known: dict[str, bytes] = {}
        self.cut = re.compile(self._cut())

    def _cut(self) -> str:
        """Words: marks and what follows; letters and other characters apart if no piece holds both side by side."""
        crossing = re.compile(f"[^{MARK}]{MARK}")
        if any(crossing.search(p) for p in self.ids):
            return r"(?s).+"
        mixed = re.compile(f"[{_LETTERS}][^{_LETTERS}{MARK}]|[^{_LETTERS}{MARK}][{_LETTERS}]")
        if any(mixed.search(p) for p in self.ids):
            return f"{MARK}*[^{MARK}]+|{MARK}+"
        return f"{MARK}*(?:[{_LETTERS}]+|[^{_LETTERS}{MARK}]+)|{MARK}+"

    def merged(self, text: str) -> list[str]:
        """Merges the best adjacent pair, the first of equals, until none is left; for short texts."""
        parts = list(text)
        while len(parts) > 1:
            best, at = None, -1
            for i in range(len(parts) - 1):
                rank = self.rank.get(parts[i] + parts[i + 1])
                if rank is not None and (best is None or rank < best):
                    best, at = rank, i
            if at < 0:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts

    def follows(self, before: int, after: int) -> bool:
        key = before << 20 | after
        told = self.pairs.get(key)
        if told is None:
            a, b = self.texts[before], self.texts[after]
            told = self.pairs[key] = self.merged(a + b) == [a, b]
        return told

    def learn(self, words: Iterable[str]) -> None:
        """Encodes distinct words in sorted order, reusing the states of shared prefixes."""
        reached, reach, pairs, follows, texts = self.reached, self.reach, self.pairs, self.follows, self.texts
        last: list[int] = [-1]  # last[e]: the last piece of the encoding of the first e characters; -1: none
        before = ""
        for word in sorted(words):
            shared = 0
            for x, y in zip(word, before):
                if x != y:
                    break
                shared += 1
            del last[shared + 1 :]
            for e in range(shared + 1, len(word) + 1):
                found = -1
                longest = reach.get(word[e - 1], 0)
                for n in range(1, min(longest, e) + 1):
                    piece = reached.get(word[e - n : e])
                    if piece is None:
                        continue
                    left = last[e - n]
                    if left < 0 or (follows(left, piece) if (told := pairs.get(left << 20 | piece)) is None else told):
                        found = piece
                        break
                last.append(found)
            out: list[int] = []
            e = len(word)
            while e:
                piece = last[e]
                if piece < 0:
                    out.extend(self.bytes[b] for b in reversed(word[e - 1].encode()))
                    e -= 1
                else:
                    out.append(piece)
                    e -= len(texts[piece])
            out.reverse()
            self.known[word] = np.array(out, dtype=np.int32).tobytes()
            before = word

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        words = [self.cut.findall(MARK + t.replace(" ", MARK)) if t else [] for t in texts]
        if len(self.known) > REMEMBERED:
            self.known.clear()
        fresh = set()
        for own in words:
            fresh.update(own)
        self.learn(fresh.difference(self.known))
        get = self.known.__getitem__
        return [np.frombuffer(b"".join(map(get, own)), dtype=np.int32) for own in words]

    def decode(self, ids: Iterable[int]) -> str:
        out = b"".join(map(self.spelled.__getitem__, ids))
        return out.removeprefix(b" ").decode("utf-8", "replace")


_CODERS: dict[str, PieceCoder] = {}


def coder(path: str) -> PieceCoder:
    if path not in _CODERS:
        _CODERS[path] = PieceCoder(path)
    return _CODERS[path]


def encode_documents(documents: DataFrame, path: str, decoded: bool = False) -> DataFrame:
    """`documents` with the ids of each text as `ids`, and on request the text that they decode to; no shuffle."""
    added = ["ids array<int>", *(["decoded string"] if decoded else [])]
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in documents.schema if f.name not in ("ids", "decoded")), *added])
    kept = [c for c in documents.columns if c not in ("ids", "decoded")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = coder(path)
        for batch in batches:
            for part in slices(batch, limit=2 << 20):
                ids = own.encode(text_column(part).to_pylist())
                ends = np.cumsum([0, *map(len, ids)]).astype(np.int32)
                columns = [part.column(i) for i in range(part.num_columns)]
                columns.append(pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([np.zeros(0, dtype=np.int32), *ids]))))
                if decoded:
                    columns.append(pa.array([own.decode(x.tolist()) for x in ids], pa.string()))
                yield pa.RecordBatch.from_arrays(columns, names=[*kept, *(x.split()[0] for x in added)])

    return documents.select(*kept).mapInArrow(run, schema)


def decode_documents(encoded: DataFrame, path: str) -> DataFrame:
    """(doc_id, text) of each row of (doc_id, ids)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = coder(path)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array([own.decode(x or ()) for x in batch.column(1).to_pylist()], pa.string())], names=["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")
