"""Chat formatting by quotation linking: which message each one answers, and its text without the quotes.

A line's quote level is the number of leading `>` marks.  Neighbouring lines of one level are one passage
(so rewrapped quotes read as the text they quote), passages are cut into sentences, and sentences are
normalised (letters and digits, lower case) and hashed.  A passage as a whole and each of its lines are
hashed as well: a quoted passage none of whose longer sentences is found is looked for as a whole, then by
lines, and one that has short sentences only at last by these.  A quoted sentence is linked to the last earlier
message of its conversation that has the sentence among its own; this is one ordered pass over each
(conversation, sentence), not a join of all quoting with all quoted messages.  A message answers the
message that most of its level-1 sentences (or what stands for them) link to, ties go to the later one; without such a link it
answers the message before it.  Deeper levels are linked too and reported.  Depths in the reply tree come
from pointer doubling; a conversation in reply order is ordered by (depth, turn), so that each message
stands after the one it answers.

A line that introduces a quote (`... wrote:` and the like) goes with the quote.

Edge cases: a null text is empty; a message without conv_id or turn is a conversation of its own, with
depth 0; repeated (conv_id, turn) rows are one message for linking and stay as rows; a quote nobody wrote
is removed from the text and linked to nothing; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import settled
from .textkit import slices, text_column

_MARKS = re.compile(r"^[ \t]{0,3}((?:>[ \t]?)+)")
_INTRODUCTION = re.compile(r"(?:wrote|writes|said|schrieb|écrit|escribió)[ \t]?:\s*$", re.I)
_SENTENCE = re.compile(r"(?<=[.!?])\s+|(?<=[。！？])\s*")
_PLAIN = re.compile(r"[\W_]+")
#: shorter sentences are linked only where a quote has no longer one
SHORTEST = 8

PARSED = "conv_id long, turn long, role string, own string, levels int, said array<long>, quoted array<struct<level: int, sentence: long, passage: int, tier: int>>"
LONG, WHOLE, LINE, SHORT = range(4)  # what a quoted passage is linked by: the first of them that is found


def _plain(part: str) -> str:
    return _PLAIN.sub(" ", part.lower()).strip()


def _hash(plain: str) -> int:
    return xxhash.xxh64_intdigest(plain.encode()) - (1 << 63)


def sentences(passage: str, shortest: int = SHORTEST) -> list[int]:
    """Hashes of a passage's normalised sentences."""
    return [_hash(x) for x in map(_plain, _SENTENCE.split(passage)) if len(x) >= shortest]


def told_by(lines: list[str]) -> list[tuple[int, int]]:
    """(tier, hash) of all that a quoted passage can be linked by."""
    passage = " ".join(lines)
    long = sentences(passage)
    out = [(LONG, h) for h in long]
    out += [(WHOLE, _hash(x)) for x in [_plain(passage)] if x]
    out += [(LINE, _hash(x)) for x in map(_plain, lines) if len(x) >= (SHORTEST if long else 1)]
    return out if long else out + [(SHORT, h) for h in sentences(passage, 1)]


def parse(text: str) -> tuple[str, int, list[int], list[tuple[int, int]]]:
    """(own text, deepest level, own sentences, quoted (level, sentence) pairs) of a message."""
    own, levels, said, quoted = read(text)
    return own, levels, said, [(level, h) for level, h, _, tier in quoted if tier in (LONG, SHORT)]


def read(text: str) -> tuple[str, int, list[int], list[tuple[int, int, int, int]]]:
    """As `parse`, with own lines and passages among the sentences, and quoted (level, hash, passage, tier) rows."""
    lines = []
    for line in text.split("\n"):
        found = _MARKS.match(line)
        lines.append((found.group(1).count(">"), line[found.end() :]) if found else (0, line))
    own, passages = [], []
    for i, (level, line) in enumerate(lines):
        if not level and _INTRODUCTION.search(line) and any(x for x, _ in lines[i + 1 : i + 2]):
            continue
        if not level:
            own.append(line)
        if passages and passages[-1][0] == level and line.strip():
            passages[-1][1].append(line)
        elif line.strip():
            passages.append((level, [line]))
        else:
            passages.append((-1, []))
    said = []
    for x in [x for level, x in passages if level == 0]:
        said += sentences(" ".join(x), 1) + [_hash(y) for y in map(_plain, [" ".join(x), *x]) if y]
    said = list(dict.fromkeys(said))
    quoted = [(level, h, i, tier) for i, (level, x) in enumerate(passages) if level > 0 for tier, h in told_by(x)]
    deepest = max((level for level, _ in lines), default=0)
    if not deepest:
        return text, 0, said, quoted
    return re.sub(r"\n{3,}", "\n\n", "\n".join(own)).strip("\n"), deepest, said, quoted


def answered(turn):
    """The turn that a message quotes when it is sent as mail: every third one goes back two turns further than the one before."""
    return F.when((turn % 3 == 2) & (turn >= 3), turn - 3).when(turn % 3 != 0, turn - 1)


def as_mail(messages: DataFrame) -> DataFrame:
    """(conv_id, turn, role, text): messages as they would be sent, each behind a quote of the one that `answered` names.

    Every line of the quoted text stands behind a mark, under a line that introduces it.  A message whose turn names
    none, or one that is not there or has no text, quotes nothing; a turn that stands twice is quoted in its smallest text.
    """
    said = messages.where("trim(text) <> ''").groupBy("conv_id", F.col("turn").alias("origin")).agg(F.min("text").alias("quoted"), F.min("role").alias("by"))
    told = messages.select("conv_id", "turn", "role", "text", answered(F.col("turn")).alias("origin")).join(said, ["conv_id", "origin"], "left")
    quote = F.concat(F.coalesce("by", F.lit("someone")), F.lit(" wrote:\n> "), F.regexp_replace("quoted", "\n", "\n> "), F.lit("\n"))
    return told.select("conv_id", "turn", "role", F.concat(F.coalesce(quote, F.lit("")), F.coalesce("text", F.lit(""))).alias("text"))


def parsed(messages: DataFrame) -> DataFrame:
    """Own text and sentences of each row of (conv_id, turn, role, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("level", pa.int32()), ("sentence", pa.int64()), ("passage", pa.int32()), ("tier", pa.int32())]))
        for batch in batches:
            for part in slices(batch):
                rows = [read(t) for t in text_column(part).to_pylist()]
                yield pa.RecordBatch.from_arrays(
                    [
                        part.column(0).cast(pa.int64()),
                        part.column(1).cast(pa.int64()),
                        part.column(2).cast(pa.string()),
                        pa.array([r[0] for r in rows], pa.string()),
                        pa.array([r[1] for r in rows], pa.int32()),
                        pa.array([r[2] for r in rows], pa.list_(pa.int64())),
                        pa.array([[dict(zip(("level", "sentence", "passage", "tier"), q)) for q in r[3]] for r in rows], kind),
                    ],
                    names=[x.split()[0] for x in ("conv_id", "turn", "role", "own", "levels", "said", "quoted")],
                )

    return messages.select("conv_id", "turn", "role", "text").mapInArrow(run, PARSED)


def links(told: DataFrame) -> DataFrame:
    """(conv_id, turn, level, origin, sentences): how many quoted sentences of a level come from which message."""
    told = told.where("conv_id is not null and turn is not null")
    quoted = told.select("conv_id", "turn", F.explode("quoted").alias("q")).select("conv_id", "turn", "q.level", "q.sentence", "q.passage", "q.tier").distinct()
    wanted = quoted.select("conv_id", "sentence").distinct()
    said = told.select("conv_id", "turn", F.explode("said").alias("sentence")).distinct().join(wanted, ["conv_id", "sentence"], "left_semi")
    order = Window.partitionBy("conv_id", "sentence").orderBy("turn").rangeBetween(Window.unboundedPreceding, -1)
    every = said.select("conv_id", "sentence", "turn", F.lit(0).alias("level")).unionByName(quoted, allowMissingColumns=True)
    found = every.withColumn("origin", F.max(F.when(F.col("level") == 0, F.col("turn"))).over(order))
    found = found.where("level > 0 and origin is not null")
    first = F.min("tier").over(Window.partitionBy("conv_id", "turn", "passage"))
    found = found.withColumn("first", first).where("tier = first")
    return found.groupBy("conv_id", "turn", "level", "origin").agg(F.countDistinct("sentence").alias("sentences"))


def depths(parents: DataFrame, most_rounds: int = 40) -> DataFrame:
    """(conv_id, turn, depth) for (conv_id, turn, origin): hops to the message that answers none.

    Messages without a link follow the one before, so a conversation is runs of messages, each of which
    starts at a linked message or at the first one.  A place in a run is a running number; only the starts
    of runs are joined, by pointer doubling over runs.
    """
    order = Window.partitionBy("conv_id").orderBy("turn")
    ranked = parents.select("conv_id", "turn", "origin", F.row_number().over(order).alias("rank"))
    starts = F.when(F.col("origin").isNotNull() | (F.col("rank") == 1), F.struct(F.col("turn").alias("start"), "rank"))
    held = ranked.withColumn("run", F.last(starts, ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, 0)))
    placed = settled(held.select("conv_id", "turn", "origin", F.col("run.start").alias("start"), (F.col("rank") - F.col("run.rank")).cast("long").alias("offset")))
    linked = placed.where("origin is not null").select("conv_id", F.col("turn").alias("start"), "origin")
    above = placed.select("conv_id", F.col("turn").alias("origin"), F.col("start").alias("up"), (F.col("offset") + 1).alias("depth"))
    state = settled(linked.join(above, ["conv_id", "origin"]).select("conv_id", "start", "up", "depth"))
    for _ in range(most_rounds):
        further = state.select("conv_id", F.col("start").alias("up"), F.col("up").alias("further"), F.col("depth").alias("more"))
        moved = settled(state.join(further, ["conv_id", "up"]).select("conv_id", "start", "further", (F.col("depth") + F.col("more")).alias("sum")))
        if moved.isEmpty():
            break
        state = settled(state.join(moved, ["conv_id", "start"], "left").select("conv_id", "start", F.coalesce("further", "up").alias("up"), F.coalesce("sum", "depth").alias("depth")))
    return placed.join(state.drop("up"), ["conv_id", "start"], "left").select("conv_id", "turn", (F.col("offset") + F.coalesce("depth", F.lit(0))).alias("depth"))


def reply_ordered(messages: DataFrame) -> DataFrame:
    """One row for each message: whom it answers, its depth, its quote links, and its text without quotes.

    `parent` is the turn it answers; `linked` says whether a quote tells so.  Order by (conv_id, depth, turn).
    """
    told = parsed(messages)
    slim = settled(told.select("conv_id", "turn", "said", "quoted"))
    found = settled(links(slim))
    best = found.where("level = 1").groupBy("conv_id", "turn").agg(F.max(F.struct("sentences", "origin"))["origin"].alias("origin"))
    listed = found.groupBy("conv_id", "turn").agg(F.array_sort(F.collect_list(F.struct("level", "origin", "sentences"))).alias("links"))
    turns = slim.where("conv_id is not null and turn is not null").select("conv_id", "turn").distinct()
    before = turns.withColumn("before", F.lag("turn").over(Window.partitionBy("conv_id").orderBy("turn")))
    parents = settled(
        before.join(best, ["conv_id", "turn"], "left").join(listed, ["conv_id", "turn"], "left").select("conv_id", "turn", "origin", F.coalesce("origin", "before").alias("parent"), F.col("origin").isNotNull().alias("linked"), "links")
    )
    placed = parents.drop("origin").join(depths(parents), ["conv_id", "turn"])
    return told.select("conv_id", "turn", "role", "own", "levels").join(placed, ["conv_id", "turn"], "left").select(
        "conv_id",
        "turn",
        "role",
        "parent",
        F.coalesce("depth", F.lit(0)).cast("long").alias("depth"),
        F.coalesce("linked", F.lit(False)).alias("linked"),
        F.col("levels").cast("long").alias("quote_levels"),
        F.coalesce("links", F.array()).alias("links"),
        F.col("own").alias("text"),
    )


def conversations(ordered: DataFrame) -> DataFrame:
    """(conv_id, messages): conversations as lists in reply order; for conversations that fit in a row."""
    message = F.struct("depth", "turn", "role", "text")
    return ordered.where("conv_id is not null").groupBy("conv_id").agg(F.array_sort(F.collect_list(message)).alias("messages"))
