"""From input tuples to a graph: both directions, relabelling, degrees, dense ids, induced subgraphs."""

from __future__ import annotations

from math import gcd

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from levelgrid.plans.state import settled


def symmetrize(edges: DataFrame, simple: bool = True) -> DataFrame:
    """Each tuple and its opposite; the simple form drops loops and repeats (one shuffle)."""
    both = edges.unionAll(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    return both.where("src <> dst").distinct() if simple else both


def multiplicity(edges: DataFrame) -> DataFrame:
    """The undirected graph without loops, with how many tuples each edge stands for."""
    return symmetrize(edges, simple=False).where("src <> dst").groupBy("src", "dst").agg(F.count("*").alias("mult"))


def relabel_affine(edges: DataFrame, n: int, a: int = 7919, b: int = 13) -> DataFrame:
    """v -> (a*v + b) mod n, a bijection that spreads neighbouring ids over all blocks."""
    while gcd(a, n) != 1:
        a += 2
    return edges.select(*(((F.col(c) * a + b) % n).alias(c) for c in ("src", "dst")))


def affine_label(v: int, n: int, a: int = 7919, b: int = 13) -> int:
    while gcd(a, n) != 1:
        a += 2
    return (a * v + b) % n


def degrees(graph: DataFrame) -> DataFrame:
    return graph.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("degree"))


def dense_ids(frame: DataFrame, by: str, name: str) -> DataFrame:
    """`frame` with 0-based ranks of distinct values: sorted ranges, their sizes summed, ranks inside each.

    No window spans the table; the driver holds one count a range.
    """
    ranged = settled(frame.repartitionByRange(by).select("*", F.spark_partition_id().alias("range")))
    sizes = {r["range"]: r["n"] for r in ranged.groupBy("range").agg(F.count("*").alias("n")).collect()}
    before, total = [], 0
    for k in range(max(sizes, default=-1) + 1):
        before.append(total)
        total += sizes.get(k, 0)
    inside = F.row_number().over(Window.partitionBy("range").orderBy(by)) - 1
    offset = F.element_at(F.array(*map(F.lit, before or [0])), F.col("range") + 1)
    return ranged.select(*frame.columns, (inside + offset).cast("long").alias(name))


def relabel_degree(edges: DataFrame) -> DataFrame:
    """Dense ids in order of falling degree, ties by old id: hubs come first."""
    counted = degrees(symmetrize(edges)).withColumn("key", F.struct((-F.col("degree")).alias("d"), "v"))
    ids = dense_ids(counted.select("key", "v"), "key", "label").select("v", "label")
    out = edges.join(ids.select(F.col("v").alias("src"), F.col("label").alias("s")), "src").join(ids.select(F.col("v").alias("dst"), F.col("label").alias("d")), "dst")
    return out.select(F.col("s").alias("src"), F.col("d").alias("dst"))


def induced(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """Edges with both ends among `vertices` (v): two semi-joins."""
    ends = edges.join(vertices.select(F.col("v").alias("src")), "src", "left_semi")
    return ends.join(vertices.select(F.col("v").alias("dst")), "dst", "left_semi").select("src", "dst")
