"""Helpers on the Spark side that several operators of this subpackage share."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levelgrid.plans.state import settled

#: words of a text, as a Java or DuckDB pattern
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def parts(frame: DataFrame) -> int:
    """How many shuffle partitions this session uses."""
    return int(frame.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def text_or_empty(name: str = "text"):
    return F.coalesce(F.col(name), F.lit(""))


__all__ = ["WORD", "parts", "settled", "table", "text_or_empty"]
