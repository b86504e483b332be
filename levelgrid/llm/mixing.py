"""Mixes sources to target weights by a low-discrepancy schedule of equal blocks of words.

`source_targets` shares the size of all sources by weight, each at most `most` times its own size and
the excess reshared.  `schedule` maps the points of a golden-ratio sequence through the cumulative
targets: slot by slot, each names a source and takes the next of its blocks of `block` words, whose rank
in the source is the slot's number among the source's slots.  A source whose target is under FINE blocks
is dealt more exactly than whole blocks allow: its slots share round(target) words evenly, and if it draws
none, it shares a slot with another source.  `shuffled_stream` puts a source's documents in hash
order and gives each the words it covers in the source's endless stream (the source over and over).
`Mix` joins the two on (source, block rank) and returns the words of each document that each slot takes.

Scale: a source can hold a third of all rows, so places in a source come from sums by hash bucket and a
running sum inside each bucket; no source meets in one task.  A table of sources, aggregated, is the only
thing that is ordered as a whole.

Edge cases: a null text has size 0 and takes nothing; a null source is a source of its own, last in
order; equal documents are ordered by doc_id and then share their places; with no words at all every
target and taken count is 0; an empty table gives no rows; `mixed_documents` keeps the table's columns,
whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, settled, text_or_empty

WEIGHTS = (5, 2, 1)
#: the golden ratio's fraction in units of 2**-31, odd: the sequence visits all of them once
GOLDEN, UNIT = 1327217885, 1 << 31
BUCKETS, CELLS, RUN = 4096, 4096, 1 << 14
SLOTS, LARGEST_BLOCK = 1 << 16, 4096
#: a source draws a few slots more or less than its share; from this many blocks on, that is about a hundredth
FINE = 512


def sized(documents: DataFrame) -> DataFrame:
    """(doc_id, source, size, row): what the plan needs, and all columns of the table in one."""
    return documents.select("doc_id", "source", F.regexp_count(text_or_empty(), F.lit(WORD)).cast("long").alias("size"), F.struct("*").alias("row"))


def source_targets(sizes: DataFrame, weights=WEIGHTS, most: int = 3) -> DataFrame:
    """source, source_size, weight, target for rows of (source, size); `source` may be null once."""
    by_code_point = Window.orderBy(F.col("source").isNull(), "source")
    cycle = F.array(*map(F.lit, weights))
    weighed = (
        sizes.groupBy("source")
        .agg(F.coalesce(F.sum("size"), F.lit(0)).alias("source_size"))
        .withColumn("weight", F.get(cycle, ((F.row_number().over(by_code_point) - 1) % len(weights)).cast("int")).cast("double"))
        .withColumn("top", F.col("source_size") * most)
    )
    everything = Window.partitionBy()
    by_ratio = Window.orderBy(F.col("top") / F.col("weight"), F.col("source").isNull(), "source")
    before = by_ratio.rowsBetween(Window.unboundedPreceding, -1)
    left = weighed.select(
        "*",
        (F.sum("source_size").over(everything) - F.coalesce(F.sum("top").over(before), F.lit(0))).alias("words_left"),
        (F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(before), F.lit(0.0))).alias("weight_left"),
    ).withColumn("full", F.col("top") * F.col("weight_left") <= F.col("weight") * F.col("words_left"))
    # the full sources come first in this order: what the first other one has left is shared by all others
    share = F.min_by(F.struct("words_left", "weight_left"), F.struct(F.col("top") / F.col("weight"), F.col("source").isNull(), F.col("source"))).over(Window.partitionBy("full"))
    return left.withColumn("share", share).select(
        "source",
        "source_size",
        "weight",
        F.when(F.col("full"), F.col("top").cast("double")).otherwise(F.col("weight") * F.col("share.words_left") / F.col("share.weight_left")).alias("target"),
    )


def schedule(targets: DataFrame, slots: int, block: int, most: int = 3) -> DataFrame:
    """source, rank, slot: the source that each slot takes from, and the slot's number among that source's slots.

    Slot number `rank` of a source ends before word (rank + 1) * words div parts of the source's endless
    stream and begins where the one before ends; the last one ends at `top`, `most` times the source's size, at most.

    A source owns a stretch of [0, 1) as long as its share.  Points and stretches meet in an equality join
    on one of CELLS equal cells; ranks are sums by runs of slots plus a running number inside each run.
    A slot that would begin beyond `top` is left out.
    """
    spark = targets.sparkSession
    ordered = Window.orderBy(F.col("source").isNull(), "source").rowsBetween(Window.unboundedPreceding, 0)
    everything = Window.partitionBy()
    stretches = targets.where("target > 0").select(
        "source", "source_size", "target", F.sum("target").over(ordered).alias("upto"), F.sum("target").over(everything).alias("whole")
    )
    top, fine = F.col("source_size") * most, F.col("target") < FINE * block
    quota = F.when(fine, F.least(F.round("target").cast("long"), top))
    stretches = stretches.select("source", top.alias("top"), quota.alias("quota"), ((F.col("upto") - F.col("target")) / F.col("whole")).alias("low"), F.when(F.col("upto") >= F.max("upto").over(everything), 1.0).otherwise(F.col("upto") / F.col("whole")).alias("high"))
    in_cell = stretches.withColumn("cell", F.explode(F.sequence(F.floor(F.col("low") * CELLS), F.least(F.floor(F.col("high") * CELLS), F.lit(CELLS - 1)))))
    points = spark.range(slots).select(F.col("id").alias("slot"), ((F.col("id") % UNIT * GOLDEN) % UNIT / F.lit(float(UNIT))).alias("point"))
    points = points.withColumn("cell", F.floor(F.col("point") * CELLS))
    drawn = points.join(in_cell, "cell").where("low <= point and point < high").select("source", "top", "quota", "slot", F.expr(f"slot div {RUN}").alias("run"))
    upto = Window.partitionBy("source").orderBy("run").rowsBetween(Window.unboundedPreceding, -1)
    runs = drawn.groupBy("source", "run").agg(F.count("*").alias("n")).select(
        F.col("source").alias("of"), F.col("run").alias("of_run"), F.coalesce(F.sum("n").over(upto), F.lit(0)).alias("before"), F.sum("n").over(Window.partitionBy("source")).alias("own_slots")
    )
    inside = F.row_number().over(Window.partitionBy("source", "run").orderBy("slot"))
    ranked = drawn.withColumn("inside", inside).join(runs, F.col("source").eqNullSafe(F.col("of")) & (F.col("run") == F.col("of_run")))
    ranked = ranked.select("source", (F.col("before") + F.col("inside") - 1).alias("rank"), "slot", "top", "quota", "own_slots")
    # a source that drew no slot shares the one at its stretch's place
    drew = runs.select("of").distinct()
    missed = stretches.where("quota > 0").join(drew, F.col("source").eqNullSafe(F.col("of")), "left_anti")
    ranked = ranked.unionByName(missed.select("source", F.lit(0).cast("long").alias("rank"), F.floor(F.col("low") * slots).alias("slot"), "top", "quota", F.lit(1).cast("long").alias("own_slots")))
    ranked = ranked.withColumn("words", F.coalesce("quota", F.lit(block).cast("long"))).withColumn("parts", F.when(F.col("quota").isNull(), 1).otherwise(F.col("own_slots")))
    return ranked.where(F.col("quota").isNotNull() | (F.col("rank") * block < F.col("top"))).select("source", "rank", "slot", "words", "parts", "top")


def paces(scheduled: DataFrame) -> DataFrame:
    """of, words, parts, reach for each source of a schedule: how its stream is cut, and the words of it that all its slots take."""
    upto = F.expr("(max(rank) + 1) * max(words) div max(parts)")
    return scheduled.groupBy(F.col("source").alias("of")).agg(F.max("words").alias("words"), F.max("parts").alias("parts"), F.least(upto, F.max("top")).alias("reach")).where("reach > 0")


def shuffled_stream(documents: DataFrame) -> DataFrame:
    """`documents` (doc_id, source, size, ...) with bucket, place and start: where each begins among its source's words."""
    key = F.conv(F.substring(F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))), 1, 12), 16, 10).cast("long")
    keyed = documents.withColumn("key", key).withColumn("bucket", F.expr(f"key div {(1 << 48) // BUCKETS}"))
    order = Window.partitionBy("source", "bucket").orderBy("key", "doc_id", "size")
    upto = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    sums = keyed.groupBy("source", "bucket").agg(F.sum("size").alias("n")).select(F.col("source").alias("of"), F.col("bucket").alias("of_bucket"), F.coalesce(F.sum("n").over(upto), F.lit(0)).alias("before"))
    placed = keyed.withColumn("place", F.row_number().over(order)).withColumn("inside", F.coalesce(F.sum("size").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    placed = placed.join(sums, F.col("source").eqNullSafe(F.col("of")) & (F.col("bucket") == F.col("of_bucket")))
    return placed.withColumn("start", F.col("before") + F.col("inside")).drop("key", "of", "of_bucket", "before", "inside")


class Mix:
    """A plan over `slim` (doc_id, source, size); its one action reads the total size and the number of documents."""

    def __init__(self, slim: DataFrame, weights=WEIGHTS, most: int = 3):
        self.slim, self.most = slim, most
        self.targets = source_targets(slim, weights, most)
        total = slim.agg(F.coalesce(F.sum("size"), F.lit(0)).alias("n")).first()["n"]
        self.block = max(1, min(LARGEST_BLOCK, -(-total // SLOTS)))
        self.slots = (total + self.block // 2) // self.block
        self.schedule = schedule(self.targets, self.slots, self.block, most)

    def with_targets(self, frame: DataFrame) -> DataFrame:
        t = self.targets.select(F.col("source").alias("of"), "source_size", "target")
        return frame.join(t, F.col("source").eqNullSafe(F.col("of"))).drop("of")

    def spans(self) -> DataFrame:
        """Every document, with the slots that take from it and the words each takes: [from_word, to_word).

        A document that no slot takes from has one row with null slot.
        """
        stream = self.with_targets(shuffled_stream(self.slim)).withColumn("lap", F.explode(F.sequence(F.lit(0), F.lit(self.most - 1))))
        stream = stream.join(paces(self.schedule), F.col("source").eqNullSafe(F.col("of")), "left").drop("of")
        begin = F.col("start") + F.col("lap") * F.col("source_size")
        stream = stream.withColumn("begin", begin).withColumn("upto", F.col("begin") + F.col("size"))
        # the slot of word w: slots of a source that takes fewer words than slots may be empty
        ranks = F.when((F.col("size") > 0) & (F.col("begin") < F.col("reach")), F.sequence(F.expr("((begin + 1) * parts - 1) div words"), F.expr("(least(upto, reach) * parts - 1) div words")))
        pieces = stream.withColumn("rank", F.explode_outer(ranks))
        taken = self.schedule.select(F.col("source").alias("of"), F.col("rank").alias("of_rank"), "slot")
        joined = pieces.join(taken, F.col("source").eqNullSafe(F.col("of")) & (F.col("rank") == F.col("of_rank")), "left")
        low = F.greatest(F.col("begin"), F.expr("rank * words div parts")) - F.col("begin")
        high = F.least(F.col("upto"), F.expr("(rank + 1) * words div parts")) - F.col("begin")
        return joined.where(F.col("slot").isNull() | (low < high)).select("doc_id", "source", "bucket", "place", "size", "source_size", "target", "lap", "slot", F.when(F.col("slot").isNotNull(), low).alias("from_word"), F.when(F.col("slot").isNotNull(), high).alias("to_word"))

    def taken(self) -> DataFrame:
        """One row for each document: the words that the mix takes from it, repeats counted."""
        words = F.coalesce(F.sum(F.col("to_word") - F.col("from_word")), F.lit(0)).cast("long")
        return self.spans().groupBy("source", "bucket", "place").agg(
            *(F.first(c).alias(c) for c in ("doc_id", "size", "source_size", "target")), words.alias("taken")
        ).select("doc_id", "size", "source_size", "target", "taken")


def slim_sizes(documents: DataFrame) -> DataFrame:
    """(doc_id, source, size) from reliable storage: the texts are read once."""
    return settled(sized(documents).select("doc_id", "source", "size"))


def mixed_documents(documents: DataFrame, weights=WEIGHTS, most: int = 3) -> DataFrame:
    """The mixed corpus with the columns of `documents`: a row for each time that the schedule takes a document.

    All slots of a source together take the words from 0 up to `reach` of its endless stream, so each
    lap over the source takes whole documents, and the last one ends inside one document, of which it takes
    the first words, joined by single spaces; n_chars follows.  Texts are shuffled once.
    """
    mix = Mix(slim_sizes(documents), weights, most)
    reach = paces(mix.schedule).select(F.col("of").alias("reach_of"), "reach")
    sources = mix.targets.select("source", "source_size").join(reach, F.col("source").eqNullSafe(F.col("reach_of"))).drop("source")
    stream = shuffled_stream(sized(documents))
    laps = stream.join(sources, F.col("source").eqNullSafe(F.col("reach_of"))).withColumn("lap", F.explode(F.sequence(F.lit(0), F.lit(most - 1))))
    words = F.least(F.col("size"), F.col("reach") - F.col("start") - F.col("lap") * F.col("source_size"))
    laps = laps.withColumn("words", words).where("words > 0")
    head = F.array_join(F.slice(F.regexp_extract_all("row.text", F.lit(f"({WORD})")), F.lit(1), F.col("words").cast("int")), " ")
    laps = laps.select("row", F.when(F.col("words") == F.col("size"), F.col("row.text")).otherwise(head).alias("text"))
    new = {"text": F.col("text"), "n_chars": F.char_length("text").cast("long")}
    return laps.select(*(new.get(c, F.col("row").getField(c)).alias(c) for c in documents.columns))
