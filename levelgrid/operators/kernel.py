"""Frontier expansion as one unit of work for each edge: the explicit mapping, and an Arrow kernel.

The frontier's degrees are summed exclusively; unit i belongs to the last frontier vertex k whose sum is
at most i, and takes that vertex's edge i - sum[k].  With groups of g units only a group's first unit
searches, the others go on from there.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def exclusive_scan(frontier: DataFrame, run: int = 1 << 16) -> DataFrame:
    """`frontier` (k, degree) with `before`, the degrees of smaller k summed: run totals first, then inside each run."""
    cut = frontier.withColumn("run", F.floor(F.col("k") / run))
    earlier = Window.orderBy("run").rowsBetween(Window.unboundedPreceding, -1)
    totals = cut.groupBy("run").agg(F.sum("degree").alias("n")).select("run", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("offset"))
    inside = Window.partitionBy("run").orderBy("k").rowsBetween(Window.unboundedPreceding, -1)
    return cut.withColumn("inside", F.coalesce(F.sum("degree").over(inside), F.lit(0))).join(totals, "run").select("k", *[c for c in frontier.columns if c != "k"], (F.col("inside") + F.col("offset")).alias("before"))


def edge_work_map(frontier: DataFrame, group: int = 1) -> DataFrame:
    """(unit, i, k, j) for each edge of a frontier (k, degree): its unit of `group` edges, its vertex and its place in the list."""
    scanned = exclusive_scan(frontier)
    edges = scanned.where("degree > 0").select("k", "before", F.explode(F.sequence(F.lit(0), F.col("degree") - 1)).alias("j"))
    return edges.select(F.floor((F.col("before") + F.col("j")) / group).alias("unit"), (F.col("before") + F.col("j")).alias("i"), "k", F.col("j").cast("long").alias("j"))


def map_units(degrees: np.ndarray, group: int = 1) -> tuple[np.ndarray, np.ndarray]:
    """(k, j) of every edge: a binary search for the first edge of each group, then steps to the next vertex."""
    before = np.concatenate([[0], np.cumsum(degrees)[:-1]]).astype(np.int64)
    total = int(np.sum(degrees))
    at = np.arange(total)
    if group == 1:
        k = np.searchsorted(before, at, side="right") - 1
        return k, at - before[k]
    heads = np.searchsorted(before, at[::group], side="right") - 1
    k = np.repeat(heads, group)[:total]
    ends = np.append(before[1:], total)
    while True:
        past = at >= ends[k]
        if not past.any():
            return k, at - before[k]
        k = k + past


def expand_cells(gathered: DataFrame, adjacency: DataFrame, group: int = 1) -> DataFrame:
    """(cell, key, value) for every edge of the gathered frontier (cell, key), one kernel call for each cell."""
    value = dict(adjacency.dtypes)["targets"][len("array<") : -1]
    schema = f"cell int, key {dict(adjacency.dtypes)['key']}, value {value}"

    def run(frontier: pa.Table, lists: pa.Table) -> pa.Table:
        keys = lists["key"].combine_chunks().to_numpy(zero_copy_only=False)
        wanted = np.unique(frontier["key"].combine_chunks().to_numpy(zero_copy_only=False)) if frontier.num_rows else np.zeros(0, dtype=keys.dtype)
        rows = np.flatnonzero(np.isin(keys, wanted))
        targets = lists["targets"].combine_chunks()
        starts = np.asarray(targets.offsets)[:-1][rows] if len(rows) else np.zeros(0, dtype=np.int64)
        sizes = (np.asarray(targets.offsets)[1:][rows] if len(rows) else starts) - starts
        k, j = map_units(sizes, group) if len(rows) else (np.zeros(0, dtype=np.int64),) * 2
        flat = targets.values.to_numpy(zero_copy_only=False) if len(rows) else np.zeros(0, dtype=np.int32)
        found = flat[starts[k] + j] if len(rows) else flat
        cell = (frontier["cell"] if frontier.num_rows else lists["cell"])[0].as_py()
        names = ["cell", "key", "value"]
        kinds = [pa.int32(), lists["key"].type, lists["targets"].type.value_type]
        return pa.table([pa.array(np.full(len(found), cell), kinds[0]), pa.array(keys[rows][k] if len(rows) else [], kinds[1]), pa.array(found, kinds[2])], names=names)

    return gathered.groupBy("cell").cogroup(adjacency.select("cell", "key", "targets").groupBy("cell")).applyInArrow(run, schema)
