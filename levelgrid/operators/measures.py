"""Cost and accuracy measures: traversed tuples, rates, traffic, phases, balance, validity, comparisons."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from levelgrid.functions.grid import GridSpec
from levelgrid.operators import codec


def tuples_traversed(edges: DataFrame, levels: DataFrame) -> int:
    """Input tuples, each once, loops and repeats counted, whose source the search reached."""
    return edges.join(levels.select(F.col("v").alias("src")), "src", "left_semi").count()


def per_root(edges: DataFrame, found: DataFrame) -> DataFrame:
    """(root, depth, vertices, tuples) of many searches (root, v, level): with its seconds, a root's rate."""
    sizes = found.groupBy("root").agg(F.max("level").alias("depth"), F.count("*").alias("vertices"))
    work = edges.join(found.select("root", F.col("v").alias("src")), "src").groupBy("root").agg(F.count("*").alias("tuples"))
    return sizes.join(work, "root", "left").select("root", "depth", "vertices", F.coalesce("tuples", F.lit(0)).alias("tuples"))


def teps(tuples: int, seconds: float) -> float:
    return tuples / seconds if seconds > 0 else float("inf")


def harmonic_mean(x: Column) -> Column:
    return F.count(x) / F.sum(1 / x)


def partner_counts(grid: GridSpec) -> dict[str, int]:
    """Cells that one cell exchanges with in a level: rows and columns of the grid, or all others."""
    return {"expand": grid.r - 1, "fold": grid.c - 1, "two_dimensional": grid.r + grid.c - 2, "one_dimensional": grid.cells - 1}


def traffic(messages: DataFrame, phase: str, nb: int) -> DataFrame:
    """Messages (level, sender, receiver, vertices) with bytes by encoding."""
    return codec.sized(messages, nb).withColumn("phase", F.lit(phase))


def traffic_totals(rows: DataFrame) -> DataFrame:
    """Sums by level, phase and both, and over all: a rollup."""
    return rows.rollup("phase", "level").agg(
        F.count("*").alias("messages"), F.sum("vertices").alias("vertices"), F.sum("bytes_list").alias("bytes_list"), F.sum("bytes_bitmap").alias("bytes_bitmap"), F.sum("bytes_auto").alias("bytes_auto")
    )


def frontier_profile(graph: DataFrame, levels: DataFrame) -> DataFrame:
    """(level, vertices, edges): the frontier's size and the sum of its degrees."""
    sizes = levels.groupBy("level").agg(F.count("*").alias("vertices"))
    work = graph.join(levels.select(F.col("v").alias("src"), "level"), "src").groupBy("level").agg(F.count("*").alias("edges"))
    return sizes.join(work, "level", "left").select("level", "vertices", F.coalesce("edges", F.lit(0)).alias("edges"))


def wasted_fold(found: DataFrame, fronts: DataFrame) -> DataFrame:
    """(level, sent, wasted): folded vertices, and those that were not news to their owner.

    A vertex is news if it becomes part of the frontier in that level with a foreign sender; the owner keeps
    one sender, so of several that send it all but one are wasted.
    """
    sent = found.where("cell <> owner").groupBy("level").agg(F.count("*").alias("sent"))
    own = found.where("cell = owner").select("cell", "value", "level")
    news = fronts.where("level > 0").select("cell", "value", "level").join(own, ["cell", "value", "level"], "left_anti").groupBy("level").agg(F.count("*").alias("news"))
    return sent.join(news, "level", "left").select("level", "sent", (F.col("sent") - F.coalesce("news", F.lit(0))).alias("wasted"))


def validate(edges: DataFrame, tree: DataFrame, root: int) -> DataFrame:
    """(check, violations) of a tree (v, level, pred) against the undirected graph (src, dst).

    Five checks: the root is its own parent at level 0 and the only such vertex; each parent edge exists;
    a child is one level below its parent; the ends of an edge differ by one level at most; an edge never
    leaves the reached set.
    """
    t = tree.select("v", "level", "pred")
    roots = t.agg(F.sum(((F.col("v") == root) & (F.col("level") == 0) & (F.col("pred") == root)).cast("long")).alias("right"), F.sum(((F.col("level") == 0) | (F.col("pred") == F.col("v"))).cast("long")).alias("such")).select(
        F.lit("root").alias("check"), (F.abs(F.coalesce("right", F.lit(0)) - 1) + F.abs(F.coalesce("such", F.lit(0)) - 1)).alias("violations")
    )
    child = t.where(F.col("v") != root)
    missing = child.join(edges.select(F.col("src").alias("pred"), F.col("dst").alias("v")), ["pred", "v"], "left_anti").agg(F.lit("parent edge").alias("check"), F.count("*").alias("violations"))
    above = child.join(t.select(F.col("v").alias("pred"), F.col("level").alias("above")), "pred", "left")
    steps = above.agg(F.lit("one level below parent").alias("check"), F.coalesce(F.sum((~F.col("level").eqNullSafe(F.col("above") + 1)).cast("long")), F.lit(0)).alias("violations"))
    ends = edges.join(t.select(F.col("v").alias("src"), F.col("level").alias("a")), "src").join(t.select(F.col("v").alias("dst"), F.col("level").alias("b")), "dst", "left")
    spans = ends.agg(F.lit("edge spans one level").alias("check"), F.coalesce(F.sum((F.abs(F.col("a") - F.col("b")) > 1).cast("long")), F.lit(0)).alias("violations"))
    leaves = ends.agg(F.lit("component covered").alias("check"), F.coalesce(F.sum(F.col("b").isNull().cast("long")), F.lit(0)).alias("violations"))
    return roots.unionAll(missing).unionAll(steps).unionAll(spans).unionAll(leaves)


def compare(a: DataFrame, b: DataFrame) -> DataFrame:
    """(v, a, b) where two results (v, level) differ, a missing row included."""
    joined = a.select("v", F.col("level").alias("a")).join(b.select("v", F.col("level").alias("b")), "v", "full_outer")
    return joined.where(~F.col("a").eqNullSafe(F.col("b")))


class PhaseTimer:
    """Seconds by phase name."""

    def __init__(self):
        self.seconds: dict[str, float] = {}

    def run(self, phase: str, work: Callable[[], object]) -> object:
        start = time.perf_counter()
        out = work()
        self.seconds[phase] = self.seconds.get(phase, 0) + time.perf_counter() - start
        return out


def shares(seconds: dict[str, float]) -> dict[str, float]:
    """Transfer (expand, fold) and update as shares of the four phases."""
    total = sum(seconds.values()) or 1.0
    return {"transfer": (seconds.get("expand", 0) + seconds.get("fold", 0)) / total, "update": seconds.get("update", 0) / total}


def speedup(seconds_one: float, seconds_p: float) -> float:
    """How many times faster p cells are than one (or a run than another)."""
    return seconds_one / seconds_p if seconds_p > 0 else float("inf")


def efficiency(seconds_one: float, seconds_p: float, p: int) -> float:
    return speedup(seconds_one, seconds_p) / p


def ratios(runs: DataFrame, other: DataFrame, on: list[str]) -> DataFrame:
    """Rates of two sets of runs (on..., teps) side by side, and how many times the first is the second."""
    joined = runs.select(*on, F.col("teps").alias("a")).join(other.select(*on, F.col("teps").alias("b")), on, "full_outer")
    return joined.withColumn("ratio", F.col("a") / F.col("b"))
