"""Edges as streams: windowed counts, duplicates within a watermark, and levels that follow insertions.

Sinks write to reliable storage in the shared checkpoint folder, batch by batch; a query is run over what
is there (`availableNow`) and its result read back.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from levelgrid.plans.state import ensure_checkpoint_dir, released, settled

EVENTS = T.StructType(
    [
        T.StructField("event_id", T.LongType()),
        T.StructField("ts", T.TimestampType()),
        T.StructField("user_id", T.LongType()),
        T.StructField("event_type", T.StringType()),
        T.StructField("value", T.DoubleType()),
        T.StructField("props", T.StringType()),
    ]
)


def edges_stream(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1, pattern: str = "events.parquet") -> DataFrame:
    """(ts, src, dst, event_id) of the events table, or of a folder of such files, as a file stream: a batch for each few files."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", pattern).option("recursiveFileLookup", "false").parquet(sf_dir)
    return raw.select("event_id", "ts", F.col("user_id").alias("src"), F.get_json_object("props", "$.k").cast("long").alias("dst"))


def _folder(spark: SparkSession) -> str:
    ensure_checkpoint_dir(spark)
    return f"{spark.sparkContext.getCheckpointDir()}/stream-{uuid.uuid4().hex}"


def run_to_end(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs a streaming query over all there is and returns its last result (complete) or all of its rows (append)."""
    spark = stream.sparkSession
    folder = _folder(spark)
    schema = stream.schema

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/rows/batch={number if mode == 'append' else 0}")

    query = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/log").trigger(availableNow=True).foreachBatch(keep).start()
    query.awaitTermination()
    return spark.read.schema(schema).parquet(f"{folder}/rows").select(schema.names)


def window_counts(stream: DataFrame, size: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """(window_start, src, edges) in tumbling or sliding windows."""
    windows = F.window("ts", size, slide) if slide else F.window("ts", size)
    counted = stream.withWatermark("ts", late).groupBy(windows.alias("w"), "src").agg(F.count("*").alias("edges"))
    return counted.select(F.col("w.start").alias("window_start"), "src", "edges")


def session_counts(stream: DataFrame, gap: str, late: str = "1 hour") -> DataFrame:
    """(session_start, src, edges): runs of a source's edges with gaps below `gap`."""
    counted = stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "src").agg(F.count("*").alias("edges"))
    return counted.select(F.col("w.start").alias("session_start"), "src", "edges")


def distinct_edges(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    """The first of equal edges within the watermark."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["src", "dst"])


def late_rows(rows: DataFrame, late: str = "1 hour", arrival: str = "event_id") -> DataFrame:
    """Rows whose source had, in order of `arrival`, a row newer by more than `late` before them: a side table."""
    newest = F.max("ts").over(Window.partitionBy("src").orderBy(F.expr(arrival)).rowsBetween(Window.unboundedPreceding, -1))
    return rows.withColumn("newest", newest).where(F.col("ts") < F.col("newest") - F.expr(f"INTERVAL {late}")).drop("newest")


class IncrementalLevels:
    """Levels from one root under edge insertions: levels only fall, so each batch relaxes from its own edges on.

    Edges are only ever added: a batch writes its new ones to a folder of its own, clustered by source, and the
    levels are one slim frame that a round replaces, its predecessor's files deleted.
    """

    def __init__(self, spark: SparkSession, root: int):
        self.spark, self.folder, self.batches = spark, f"{_folder(spark)}/edges", 0
        self.levels = settled(spark.range(root, root + 1).select(F.col("id").alias("v"), F.lit(0).alias("level")))

    def edges(self) -> DataFrame:
        """All edges so far, in both directions."""
        if not self.batches:
            return self.spark.createDataFrame([], "src long, dst long")
        return self.spark.read.schema("src long, dst long").parquet(*(f"{self.folder}/{i}" for i in range(self.batches)))

    def insert(self, batch: DataFrame, number: int = 0) -> None:
        both = batch.select("src", "dst").unionAll(batch.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).where("src <> dst").distinct()
        both.join(self.edges(), ["src", "dst"], "left_anti").repartition("src").sortWithinPartitions("src").write.mode("overwrite").parquet(f"{self.folder}/{self.batches}")
        touched = self.spark.read.schema("src long, dst long").parquet(f"{self.folder}/{self.batches}")
        self.batches += 1
        while True:
            offered = touched.join(self.levels, touched["src"] == self.levels["v"]).groupBy(F.col("dst").alias("w")).agg((F.min("level") + 1).alias("offer"))
            better = settled(offered.join(self.levels, F.col("w") == F.col("v"), "left").where("level is null or offer < level").select("w", F.col("offer").cast("int").alias("offer")))
            if better.isEmpty():
                return
            before = self.levels
            self.levels = settled(before.join(better, F.col("v") == F.col("w"), "full_outer").select(F.coalesce("w", "v").alias("v"), F.coalesce("offer", "level").alias("level")))
            released(before)
            touched = self.edges().join(better.select(F.col("w").alias("src")), "src", "left_semi")

    def follow(self, stream: DataFrame) -> DataFrame:
        """Takes a stream of (src, dst) to its end, batch by batch; (v, level) after it."""
        query = stream.select("src", "dst").writeStream.option("checkpointLocation", f"{_folder(stream.sparkSession)}/log").trigger(availableNow=True).foreachBatch(self.insert).start()
        query.awaitTermination()
        return self.levels
