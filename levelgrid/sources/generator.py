"""The generator as a Spark data source: `spark.read.format("rmat").option("scale", 20).load()`, also as a stream."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

from levelgrid.sources.graphs import PRIME, SEED_STEP, SHIFT, SPREAD, STEP, drift

CUTS = tuple(round(x * PRIME) for x in (0.57, 0.76, 0.95))
BATCH = 1 << 16


def tuples_of(ids: np.ndarray, scale: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """(src, dst) of some tuple numbers; the same numbers as the Column form."""
    x = ((ids * SPREAD + seed * SEED_STEP + SHIFT) % (PRIME - 1) + 1) * (STEP * SPREAD % PRIME) % PRIME
    lap = ids // (PRIME - 1)
    src, dst = np.zeros_like(ids), np.zeros_like(ids)
    for k in range(scale):
        state = (x * pow(STEP, k, PRIME) + lap * drift(k)) % PRIME
        quadrant = np.searchsorted(np.array(CUTS), state, side="right")
        src = src * 2 + (quadrant >> 1)
        dst = dst * 2 + (quadrant & 1)
    return src, dst


class _Range(InputPartition):
    def __init__(self, low: int, high: int):
        self.low, self.high = low, high


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.scale, self.seed = int(options.get("scale", 10)), int(options.get("seed", 42))
        self.total = int(options.get("edgefactor", 16)) << self.scale
        self.parts = int(options.get("partitions", max(1, self.total >> 20)))

    def partitions(self) -> list[InputPartition]:
        cuts = [self.total * i // self.parts for i in range(self.parts + 1)]
        return [_Range(a, b) for a, b in zip(cuts, cuts[1:])]

    def read(self, partition: _Range) -> Iterator[pa.RecordBatch]:
        for low in range(partition.low, partition.high, BATCH):
            src, dst = tuples_of(np.arange(low, min(low + BATCH, partition.high), dtype=np.int64), self.scale, self.seed)
            yield pa.RecordBatch.from_arrays([pa.array(src), pa.array(dst)], names=["src", "dst"])


class _Stream(SimpleDataSourceStreamReader):
    """A batch of `rows` tuples at a time, up to the generator's end."""

    def __init__(self, options: dict):
        self.own, self.rows = _Reader(options), int(options.get("rows", 10_000))

    def initialOffset(self) -> dict:  # noqa: N802
        return {"at": 0}

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        end = {"at": min(self.own.total, start["at"] + self.rows)}
        return self.readBetweenOffsets(start, end), end

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:  # noqa: N802
        src, dst = tuples_of(np.arange(start["at"], end["at"], dtype=np.int64), self.own.scale, self.own.seed)
        return iter(list(zip(src.tolist(), dst.tolist())))


class RmatSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "rmat"

    def schema(self) -> str:
        return "src long, dst long"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:  # noqa: N802
        return _Stream(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(RmatSource)
