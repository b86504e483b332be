"""Keeping the state of a loop: reliable checkpoints, and settings that hold only inside it."""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """The cluster names its shared folder in spark.checkpoint.dir; only where it is unset (tests) one is set here."""
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        context.setCheckpointDir(spark.conf.get("spark.checkpoint.dir", None) or "/tmp/levelgrid-checkpoints")


#: rows of slim state that one checkpoint file takes
ROWS_A_FILE = 100_000


def settled(frame: DataFrame, rows: int | None = None) -> DataFrame:
    """The same rows from reliable storage, with their lineage cut.

    `rows`, where it is known, bounds how many there are: small state is then written by as few tasks as
    there are cores, not in a file for each shuffle partition; large state keeps its partitions.
    """
    ensure_checkpoint_dir(frame.sparkSession)
    if rows is not None:
        frame = frame.coalesce(max(frame.sparkSession.sparkContext.defaultParallelism, -(-rows // ROWS_A_FILE)))
    return frame.checkpoint(eager=True)


def released(*frames: DataFrame) -> None:
    """Deletes the checkpoint files of settled frames that nothing will read again."""
    for frame in frames:
        file = frame._jdf.logicalPlan().rdd().getCheckpointFile()
        if file.isDefined():
            context = frame.sparkSession.sparkContext
            path = context._jvm.org.apache.hadoop.fs.Path(file.get())
            path.getFileSystem(context._jsc.hadoopConfiguration()).delete(path, True)


@contextmanager
def held(spark: SparkSession, settings: dict[str, str]) -> Iterator[None]:
    """Session settings for a block, as they were before afterwards."""
    before = {k: spark.conf.get(k, None) for k in settings}
    try:
        for k, v in settings.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
