"""Quality rules: counted base rules, and the divergence of a text from its language's reference.

A text's histograms over character classes and over common words are compared with those of its
language by Jensen-Shannon distance (base 2, 0 to 1).  The references are gathered from all documents of
the table, by language (`de-AT` counts as `de`).  A text without a language is held against the reference of
each language and rejected only if it is far from all of them; where the language whose common words it has
most of has no reference of MIN_REFERENCE words, or the language given is outside the fixed lists, nothing
says how its texts look, and the base rules alone decide.  The distances told are then those of the nearest
reference, or of all documents if there is none.
Histograms of short texts are noise, so a text is judged by character classes only from MIN_CHARS
classified characters and by common words only from MIN_WORDS words on.

Edge cases: a null text has no words; it fails the base rules, as all texts under 50 words do; an empty
language is none; repeated rows give repeated results; an empty table gives no
rows and needs no reference; `filtered_documents` keeps the table's columns.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .textkit import PUNCT, SPACE, grams, mix64, per_document, slices, split_words, text_buffer, text_column

#: fixed values: frequent words of each language
COMMON = {
    "en": "the of and to in a is that for it as was with be by on not he his but at are this have from or had an they which you were".split(),
    "de": "der die und in den von zu das mit sich des auf für ist im dem nicht ein eine als auch es an werden aus er hat dass sie nach".split(),
    "fr": "de la le et les des en un du une que est pour qui dans par plus pas au sur ne se ce il sont avec son aux ou mais".split(),
    "es": "de la que el en y a los se del las un por con no una su para es al lo como más o pero sus le ha me si".split(),
}
LANGUAGES = (*COMMON, "")  # the last one: all documents
_WORDS = sorted({w for words in COMMON.values() for w in words})
#: fixed values: classes of characters, by first byte
CLASSES = ("lower", "upper", "digit", "space", "newline", "point", "quote", "symbol", "bracket", "control", "latin", "wide", "other")
_CLASS = np.full(256, len(CLASSES), dtype=np.uint8)
for _name, _bytes in {
    "lower": range(0x61, 0x7B),
    "upper": range(0x41, 0x5B),
    "digit": range(0x30, 0x3A),
    "space": (0x20, 0x09),
    "newline": (0x0A, 0x0D),
    "point": b".,;:!?-",
    "quote": b"'\"`",
    "symbol": b"#*$%&|<>@+=/\\^~_",
    "bracket": b"()[]{}",
    "control": [b for b in [*range(0x20), 0x7F] if b not in (0x09, 0x0A, 0x0D)],
    "latin": range(0xC2, 0xCB),
    "wide": range(0xE0, 0xF0),
    "other": [*range(0xCB, 0xE0), *range(0xF0, 0x100), 0xC0, 0xC1],
}.items():
    _CLASS[list(_bytes)] = CLASSES.index(_name)
_SYMBOL = np.zeros(256, dtype=bool)
_SYMBOL[list(b"#*$%&|<>")] = True

MIN_WORDS, MAX_REPEAT = 50, 50
MIN_CHARS = 200
#: a reference of fewer words doesn't judge texts that lack a language
MIN_REFERENCE = 1000
MAX_CLASS_DISTANCE, MAX_WORD_DISTANCE = 0.30, 0.37

FIGURES = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, class_distance double, word_distance double, kept boolean"


def _common_words() -> tuple[np.ndarray, np.ndarray]:
    buf, offsets = text_buffer(pa.array([" ".join(_WORDS)]))
    values = split_words(buf, offsets, PUNCT, lower=True).value
    order = np.argsort(values)
    return values[order], order


def histograms(buf: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Counts of each document: by character class, and by common word with all other words last."""
    docs = len(offsets) - 1
    width = len(CLASSES) + 1
    owner = np.repeat(np.arange(docs, dtype=np.int64) * width, np.diff(offsets))
    classes = np.bincount(owner + _CLASS[buf], minlength=docs * width).reshape(docs, width)[:, :-1]
    words = split_words(buf, offsets, PUNCT, lower=True)
    values, order = _common_words()
    at = np.minimum(np.searchsorted(values, words.value), len(values) - 1)
    which = np.where(values[at] == words.value, order[at], len(_WORDS))
    width = len(_WORDS) + 1
    common = np.bincount(words.doc.astype(np.int64) * width + which, minlength=docs * width).reshape(docs, width)
    return classes, common


def distance(counts: np.ndarray, reference: np.ndarray) -> np.ndarray:
    """Jensen-Shannon distance of each row of counts from a reference histogram."""
    total = counts.sum(axis=1, keepdims=True)
    p = counts / np.maximum(total, 1)
    q = np.broadcast_to(reference / max(reference.sum(), 1), p.shape)
    m = (p + q) / 2

    def entropy(x: np.ndarray) -> np.ndarray:
        return -(x * np.log2(np.where(x > 0, x, 1))).sum(axis=1)

    return np.sqrt(np.maximum(0, entropy(m) - (entropy(p) + entropy(q)) / 2))


@dataclass
class References:
    """Histograms of each language, over all documents."""

    classes: dict[str, np.ndarray]
    common: dict[str, np.ndarray]


def _labels(batch: pa.RecordBatch) -> list[str]:
    """The language given with each document, without its region; empty if there is none."""
    return [re.split("[-_]", (x or "").strip().lower())[0] for x in batch.column(batch.schema.get_field_index("lang")).to_pylist()]


def _languages(batch: pa.RecordBatch) -> list[str]:
    return [x if x in COMMON else "" for x in _labels(batch)]


def references(documents: DataFrame) -> References:
    """One pass over all documents; at most one row of counts for each task and language leaves a task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = np.zeros((len(LANGUAGES), len(CLASSES) + len(_WORDS) + 1), dtype=np.int64)
        for batch in batches:
            for part in slices(batch):
                counts = np.hstack(histograms(*text_buffer(text_column(part))))
                np.add.at(sums, [LANGUAGES.index(x) for x in _languages(part)], counts)
        yield pa.RecordBatch.from_arrays([pa.array(LANGUAGES), pa.array(sums.tolist(), pa.list_(pa.int64()))], names=["lang", "counts"])

    rows = documents.select("text", "lang").mapInArrow(run, "lang string, counts array<long>").selectExpr("lang", "posexplode(counts) as (bin, n)").groupBy("lang", "bin").sum("n").collect()
    sums = {x: np.zeros(len(CLASSES) + len(_WORDS) + 1) for x in LANGUAGES}
    for lang, bin_, n in rows:
        sums[lang][bin_] = n
    sums[""] = sum(sums.values())
    # the reference of a language has its own common words; all others count as other words
    for lang in COMMON:
        foreign = [len(CLASSES) + i for i, w in enumerate(_WORDS) if w not in COMMON[lang]]
        sums[lang][-1] += sums[lang][foreign].sum()
        sums[lang][foreign] = 0
    return References({x: v[: len(CLASSES)] for x, v in sums.items()}, {x: v[len(CLASSES) :] for x, v in sums.items()})


def repeated_lines(texts: list[bytes]) -> list[int]:
    out = []
    for text in texts:
        lines = [x for x in text.split(b"\n") if x.strip()] if b"\n" in text else ()
        out.append(len(lines) - len(set(lines)))
    return out


def repeated_words(words) -> np.ndarray:
    """Words of each document in three-word windows that it has twice or more."""
    values, at = grams(words, 3)
    keys = values ^ mix64(words.doc[at].astype(np.uint64), 3)
    order = np.argsort(keys)
    same = keys[order][1:] == keys[order][:-1]
    twice = np.zeros(len(keys), dtype=bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    covered = np.zeros(len(words.value), dtype=bool)
    for j in range(3):
        covered[at[twice] + j] = True
    return per_document(covered, words.first)


def base_figures(column: pa.Array) -> dict[str, np.ndarray]:
    buf, offsets = text_buffer(column)
    words = split_words(buf, offsets, SPACE)
    heads = ((buf & 0xC0) != 0x80) & ~SPACE[buf]
    out = {
        "n_words": words.counts,
        "word_chars": per_document(heads, offsets),
        "n_symbols": per_document(_SYMBOL[buf], offsets),
        "n_dup_lines": np.array(repeated_lines(column.cast(pa.large_binary()).to_pylist()), dtype=np.int64),
        "n_repeat_words": repeated_words(words),
    }
    out["base_failed"] = (out["n_words"] < MIN_WORDS) | (100 * out["n_repeat_words"] > MAX_REPEAT * out["n_words"])
    return out


def _compared(classes: np.ndarray, common: np.ndarray, known: References, lang: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Class distance and word distance of each row from a language's reference, and whether it is far from it."""
    own = common.copy()
    if lang:
        foreign = [i for i, w in enumerate(_WORDS) if w not in COMMON[lang]]
        own[:, -1] += own[:, foreign].sum(axis=1)
        own[:, foreign] = 0
    by_class, by_word = distance(classes, known.classes[lang]), distance(own, known.common[lang])
    far = (classes.sum(axis=1) >= MIN_CHARS) & (by_class > MAX_CLASS_DISTANCE)
    far |= (common.sum(axis=1) >= MIN_WORDS) & (by_word > MAX_WORD_DISTANCE)
    return by_class, by_word, far


def _nearest(classes: np.ndarray, common: np.ndarray, known: References) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """As `_compared`, for texts of any language: from the nearest reference; far only if far from all that could tell."""
    present = [x for x in COMMON if known.common[x].sum() >= MIN_REFERENCE]
    if not present:
        by_class, by_word, far = _compared(classes, common, known, "")
        return by_class, by_word, np.zeros_like(far)
    told = [_compared(classes, common, known, x) for x in present]
    by_class, by_word, far = (np.stack(x) for x in zip(*told))
    best = np.argmin(by_word + 2 * far, axis=0), np.arange(len(classes))
    # the language that most of the common words are from
    covered = np.stack([common[:, [i for i, w in enumerate(_WORDS) if w in COMMON[x]]].sum(axis=1) for x in COMMON])
    most = covered.max(axis=0)
    absent = np.array([x not in present for x in COMMON])[:, None] & (covered == most) & (most > 0)
    return by_class[best], by_word[best], far.all(axis=0) & ~absent.any(axis=0)


def verdicts(part: pa.RecordBatch, known: References) -> dict[str, np.ndarray]:
    column = text_column(part)
    out = base_figures(column)
    buf, offsets = text_buffer(column)
    classes, common = histograms(buf, offsets)
    labels, langs = np.array(_labels(part), dtype=object), np.array(_languages(part), dtype=object)
    out["class_distance"], out["word_distance"] = np.zeros(len(langs)), np.zeros(len(langs))
    strange = np.zeros(len(langs), dtype=bool)
    for lang in set(langs.tolist()):
        rows = langs == lang
        told = _compared(classes[rows], common[rows], known, lang) if lang else _nearest(classes[rows], common[rows], known)
        out["class_distance"][rows], out["word_distance"][rows], strange[rows] = told
    strange &= (langs != "") | (labels == "")
    out["kept"] = ~out["base_failed"] & ~strange
    return out


def quality_figures(documents: DataFrame, known: References | None = None) -> DataFrame:
    """All figures, both distances and the verdict for each row of (doc_id, text, lang)."""
    known = known or references(documents)
    names = [x.split()[0] for x in FIGURES.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch):
                out = verdicts(part, known)
                yield pa.RecordBatch.from_arrays([part.column(0).cast(pa.int64()), *(pa.array(out[x]) for x in names[1:])], names=names)

    return documents.select("doc_id", "text", "lang").mapInArrow(run, FIGURES)


def filtered_documents(documents: DataFrame) -> DataFrame:
    """The documents that the rules keep, with their columns; no shuffle."""
    known = references(documents)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch):
                yield part.filter(pa.array(verdicts(part, known)["kept"]))

    return documents.mapInArrow(run, documents.schema)


