"""Table functions for SQL users: the edge-work mapping, and bitmaps to rows."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


class EdgeWork:
    """Rows (unit, i, k, j) for a list of degrees and a group size."""

    def eval(self, degrees: list, group: int) -> Iterator[tuple]:
        from levelgrid.operators.kernel import map_units

        k, j = map_units(np.array(degrees, dtype=np.int64), int(group))
        for i, (a, b) in enumerate(zip(k.tolist(), j.tolist())):
            yield i // group, i, a, b


class UnpackBits:
    """The set bits of a bitmap, from `base` on."""

    def eval(self, bits: bytes, base: int) -> Iterator[tuple]:
        for x in np.flatnonzero(np.unpackbits(np.frombuffer(bytes(bits), dtype=np.uint8), bitorder="little")).tolist():
            yield (x + base,)


def register_udtfs(spark: SparkSession) -> None:
    spark.udtf.register("edge_work", udtf(EdgeWork, returnType="unit long, i long, k long, j long"))
    spark.udtf.register("unpack_bits", udtf(UnpackBits, returnType="v long"))
