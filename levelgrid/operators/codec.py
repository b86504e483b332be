"""Message encodings: a list of 32-bit indices, or a bitmap over the receiver's block; and the switch.

A message of n indices into nb places takes 4n bytes as a list and ceil(nb / 8) as a bitmap; from
T = nb div 32 on, a list is the longer one.  A message travels in buckets of 2**15 places; a bucket's bitmap
is an array of 64-bit words, so packing, merging and unpacking are JVM expressions and aggregations: they
run where the rows are, keep their placement and need no exchange but the message's own.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

BUCKET_BITS, WORD_BITS = 1 << 15, 64
INDEX_BYTES, WORD_BYTES = 4, 8


def bucket(index: Column) -> Column:
    return F.shiftright(index, BUCKET_BITS.bit_length() - 1).cast("int")


def place(index: Column) -> Column:
    return index.bitwiseAND(BUCKET_BITS - 1).cast("int")


def word(index: Column) -> Column:
    return F.shiftright(index, 6).cast("int")


def bit(index: Column) -> Column:
    """The index as a bit of its word."""
    return F.call_function("shiftleft", F.lit(1).cast("long"), index.bitwiseAND(WORD_BITS - 1).cast("int"))


def bit_set(bits: Column, index: Column) -> Column:
    """Whether the index's bit of its word is set."""
    return bits.bitwiseAND(bit(index)) != 0


def bitmap_bytes(nb: int) -> int:
    return -(-nb // 8)


def switch_threshold(nb: int, index_bits: int = 32) -> int:
    """Indices up to which a list is sent."""
    return nb // index_bits


def sized(messages: DataFrame, nb: int) -> DataFrame:
    """`messages` (..., vertices) with bytes_list, bytes_bitmap, bytes_auto and the encoding that auto takes."""
    big = F.col("vertices") > switch_threshold(nb)
    return messages.select(
        "*",
        (F.col("vertices") * INDEX_BYTES).alias("bytes_list"),
        F.lit(bitmap_bytes(nb)).cast("long").alias("bytes_bitmap"),
        F.when(big, F.lit(bitmap_bytes(nb))).otherwise(F.col("vertices") * INDEX_BYTES).cast("long").alias("bytes_auto"),
        F.when(big, "bitmap").otherwise("list").alias("kind"),
    )


def words_of(nb: int, of_bucket: Column) -> Column:
    """Words of one bucket's bitmap: the last bucket may be short."""
    return F.least(F.lit(BUCKET_BITS // WORD_BITS), F.ceil((F.lit(nb) - of_bucket.cast("long") * BUCKET_BITS) / WORD_BITS)).cast("int")


def pack(indices: DataFrame, keys: list[str], index: str) -> DataFrame:
    """(keys, bucket, held, idx, set_words): the indices of each key by buckets, as a list and as words with a bit set.

    It is one aggregation by (keys, bucket) over one by words: rows that are placed by a key stay where they are.
    """
    rows = indices.select(*keys, bucket(F.col(index)).alias("bucket"), place(F.col(index)).alias("place"))
    by_word = rows.groupBy(*keys, "bucket", word(F.col("place")).alias("word")).agg(F.bit_or(bit(F.col("place"))).alias("bits"), F.collect_list("place").alias("places"))
    return by_word.groupBy(*keys, "bucket").agg(
        F.sum(F.size("places")).cast("long").alias("held"), F.flatten(F.collect_list("places")).alias("idx"), F.map_from_entries(F.collect_list(F.struct("word", "bits"))).alias("set_words")
    )


def messages(indices: DataFrame, keys: list[str], index: str, nb: int, codec: str = "auto") -> DataFrame:
    """(keys, bucket, kind, n, idx, words): one message for each key, in buckets; n counts the whole message.

    A bitmap covers the whole block, so its buckets without an index are there as well, all zeros; a list has none.
    """
    if codec not in ("list", "bitmap", "auto"):
        raise ValueError(f"codec is 'list', 'bitmap' or 'auto', not {codec!r}")
    kind = F.when(F.col("n") > switch_threshold(nb), "bitmap").otherwise("list") if codec == "auto" else F.lit(codec)
    dense = F.transform(F.sequence(F.lit(0), words_of(nb, F.col("bucket")) - 1), lambda w: F.coalesce(F.element_at("set_words", w), F.lit(0).cast("long")))
    message, buckets = Window.partitionBy(*keys).orderBy("bucket"), -(-nb // BUCKET_BITS)
    whole = message.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    first = F.when(F.lag("bucket").over(message).isNull(), 0).otherwise(F.col("bucket"))
    last = F.coalesce(F.lead("bucket").over(message), F.lit(buckets)) - 1
    out = pack(indices, keys, index).select("*", F.sum("held").over(whole).alias("n"), first.alias("first"), last.alias("last")).withColumn("kind", kind)
    out = out.select(*keys, "bucket", "first", "last", "kind", "n", F.when(F.col("kind") == "list", F.col("idx")).alias("idx"), F.when(F.col("kind") == "bitmap", dense).alias("words"))
    if buckets > 1 and codec != "list":
        out = out.withColumn("at", F.explode(F.when(F.col("kind") == "list", F.array("bucket")).otherwise(F.sequence("first", "last"))))
        zeros = F.array_repeat(F.lit(0).cast("long"), words_of(nb, F.col("at")))
        out = out.withColumn("words", F.when((F.col("kind") == "list") | (F.col("at") == F.col("bucket")), F.col("words")).otherwise(zeros)).withColumn("bucket", F.col("at"))
    return out.select(*keys, "bucket", "kind", "n", "idx", "words")


def payload() -> Column:
    """Bytes of a message row's list or bitmap."""
    return F.when(F.col("kind") == "list", F.size("idx") * INDEX_BYTES).otherwise(F.size("words") * WORD_BYTES).cast("long")


def unpack(sent: DataFrame, keys: list[str], index: str) -> DataFrame:
    """(keys, index): one row for each index, from lists and bitmaps alike, where the messages are."""
    places = F.sequence(F.lit(0), F.lit(WORD_BITS - 1))
    own = lambda w, i: F.when(w != 0, F.transform(F.filter(places, lambda b: bit_set(w, b)), lambda b: i * WORD_BITS + b)).otherwise(F.array().cast("array<int>"))
    held = F.when(F.col("kind") == "list", F.col("idx")).otherwise(F.flatten(F.transform("words", own)))
    rows = sent.select(*keys, "bucket", F.explode(held).alias("place"))
    return rows.select(*keys, (F.col("bucket").cast("long") * BUCKET_BITS + F.col("place")).alias(index))
