"""Licence notices in texts: exact phrases, and fuzzy short notices within a bounded number of edits.

A text is brought to its words (A-Z lowered, words by `textkit.PUNCT`) joined by single spaces.  A notice
that may have k edits is split into k + 1 pieces; by the pigeonhole principle one of them stands unedited
in every match, so only places around exact pieces are candidates.  There the regex library's
bounded-error matching verifies the edits, and its best match around a verified place gives the least edits and the span.

Edge cases: a null or wordless text has no finding, no label and score 0; other columns are ignored;
repeated rows give repeated results; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .textkit import _LOWER, PUNCT, slices, text_column

#: fixed values: exact phrases and their labels
BASE = (("mit license", "mit"), ("apache license", "apache"), ("general public license", "gpl"))
#: fixed values: opening words of common notices, as words joined by spaces
NOTICES = (
    ("mit license", "mit"),
    ("permission is hereby granted free of charge to any person obtaining a copy", "mit"),
    ("apache license version 2 0", "apache"),
    ("gnu general public license", "gpl"),
    ("general public license", "gpl"),
    ("gnu lesser general public license", "lgpl"),
    ("gnu affero general public license", "agpl"),
    ("redistribution and use in source and binary forms with or without modification", "bsd"),
    ("mozilla public license", "mpl"),
    ("eclipse public license", "epl"),
    ("permission to use copy modify and or distribute this software for any purpose", "isc"),
    ("this is free and unencumbered software released into the public domain", "unlicense"),
    ("licensed under cc by nc", "cc-by-nc"),
    ("licensed under cc by sa", "cc-by-sa"),
    ("creative commons attribution", "cc"),
)
_TABLE = bytes(0x20 if PUNCT[_LOWER[b]] else int(_LOWER[b]) for b in range(256))

FINDINGS = "array<struct<label: string, exact: boolean, first_word: long, last_word: long, edits: int, score: double>>"


def edits_allowed(phrase: str) -> int:
    """One edit for each ten characters, four at most."""
    return max(1, min(4, len(phrase) // 10))


@dataclass(frozen=True)
class Seed:
    piece: bytes
    at: int


def seeds(phrase: str, edits: int) -> list[Seed]:
    cuts = [round(i * len(phrase) / (edits + 1)) for i in range(edits + 2)]
    return [Seed(phrase[a:b].encode(), a) for a, b in zip(cuts, cuts[1:])]


def places(text: bytes, piece: bytes) -> Iterator[int]:
    at = text.find(piece)
    while at >= 0:
        yield at
        at = text.find(piece, at + 1)


def _windows(text: bytes, parts: list[Seed], length: int, edits: int) -> list[tuple[int, int]]:
    """Merged byte ranges that can hold a match; each is a little longer than the phrase, or several of them."""
    found = sorted((max(0, p - s.at - edits - 2), min(len(text), p - s.at + length + edits + 2)) for s in parts for p in places(text, s.piece))
    merged: list[tuple[int, int]] = []
    for a, b in found:
        if merged and a <= merged[-1][1]:
            merged[-1] = (merged[-1][0], max(b, merged[-1][1]))
        else:
            merged.append((a, b))
    return merged


class Scanner:
    def __init__(self, base=BASE, notices=NOTICES):
        import regex

        self.base = [(f" {p} ".encode(), len(p.split()), label) for p, label in base]
        self.fuzzy = []
        for phrase, label in notices:
            k = edits_allowed(phrase)
            bounded = rb"(?<= )(?:" + regex.escape(phrase.encode(), literal_spaces=True) + rb"){e<=%d}(?= )" % k
            self.fuzzy.append((regex.compile(bounded), regex.compile(rb"(?b)" + bounded), seeds(phrase, k), len(phrase), k, label))

    @staticmethod
    def _matches(joined: bytes, pattern, best, a: int, b: int, k: int) -> Iterator:
        """Matches in [a, b) one after another, each the best one that overlaps the first place that matches at all."""
        while m := pattern.search(joined, a, b):
            # what begins later than the first match ends is the next one's
            m = best.search(joined, m.start(), min(b, m.end() + k + 1)) or m
            yield m
            a = max(a + 1, m.end())

    def scan(self, text: bytes) -> tuple[int, list[dict]]:
        """Words of the text, and its findings in the order of the phrase tables."""
        words = text.translate(_TABLE).split()
        joined = b" " + b" ".join(words) + b" "
        out = []
        for phrase, n, label in self.base:
            seen, counted = 0, 0
            for at in places(joined, phrase):
                seen += joined.count(b" ", counted, at)
                counted = at
                out.append({"label": label, "exact": True, "first_word": seen, "last_word": seen + n - 1, "edits": 0, "score": 1.0})
        for pattern, best, parts, length, k, label in self.fuzzy:
            seen, counted = 0, 0
            for a, b in _windows(joined, parts, length, k):
                for m in self._matches(joined, pattern, best, a, b, k):
                    seen += joined.count(b" ", counted, m.start())
                    counted, first = m.start(), seen - 1
                    edits = sum(m.fuzzy_counts)
                    span = m.group().strip(b" ")
                    out.append({"label": label, "exact": False, "first_word": first, "last_word": first + span.count(b" "), "edits": edits, "score": 1.0 - edits / length})
        return len(words), closest(out)


def closest(found: list[dict]) -> list[dict]:
    """Without the fuzzy findings that a finding with another label, fewer edits and no fewer words overlaps."""
    by_place = sorted(found, key=lambda x: (x["first_word"], x["last_word"]))
    out, near = [], 0
    longest = max((x["last_word"] - x["first_word"] for x in found), default=0)
    for x in by_place:
        while by_place[near]["first_word"] + longest < x["first_word"]:
            near += 1
        worse = False
        for y in by_place[near:]:
            if y["first_word"] > x["last_word"]:
                break
            worse |= not x["exact"] and y["label"] != x["label"] and y["last_word"] >= x["first_word"] and y["edits"] < x["edits"] and y["last_word"] - y["first_word"] >= x["last_word"] - x["first_word"]
        if not worse:
            out.append(x)
    return out


def scan_licenses(documents: DataFrame, base=BASE, notices=NOTICES) -> DataFrame:
    """doc_id, n_words and all findings of each row of (doc_id, text)."""
    schema = f"doc_id long, n_words long, findings {FINDINGS}"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(base, notices)
        kind = pa.list_(pa.struct([("label", pa.string()), ("exact", pa.bool_()), ("first_word", pa.int64()), ("last_word", pa.int64()), ("edits", pa.int32()), ("score", pa.float64())]))
        for batch in batches:
            for part in slices(batch):
                found = [scanner.scan(t) for t in text_column(part).cast(pa.large_binary()).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0).cast(pa.int64()), pa.array([n for n, _ in found], pa.int64()), pa.array([x for _, x in found], kind)], names=["doc_id", "n_words", "findings"])

    return documents.select("doc_id", "text").mapInArrow(run, schema)


def license_summary(found: DataFrame) -> DataFrame:
    """One row for each document: counts, first and last exact place, labels, the best score, and the spans of all findings."""
    exact = F.filter("findings", lambda x: x["exact"])
    starts = F.transform("exact", lambda x: x["first_word"])
    names = lambda column: F.array_join(F.array_sort(F.array_distinct(F.transform(column, lambda x: x["label"]))), ",")
    return found.withColumn("exact", exact).select(
        "doc_id",
        "n_words",
        F.size("exact").cast("long").alias("n_base"),
        F.array_min(starts).alias("first_word"),
        F.array_max(starts).alias("last_word"),
        names("exact").alias("base_labels"),
        names("findings").alias("labels"),
        F.coalesce(F.array_max(F.transform("findings", lambda x: x["score"])), F.lit(0.0)).alias("score"),
        F.transform("findings", lambda x: F.struct(x["label"].alias("label"), x["first_word"].alias("first_word"), x["last_word"].alias("last_word"), x["edits"].alias("edits"))).alias("spans"),
    )
