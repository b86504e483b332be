"""Connected components of an edge list by alternating large-star and small-star rewiring.

Each round hangs every vertex's larger neighbours on the smallest vertex it sees, then its smaller ones;
the number of rounds grows with the logarithm of the component size, whatever the diameter.  Rounds are
joins and partial aggregations on vertex ids: no neighbour list is collected, and the few hubs that hold more than a
thousandth of all rows are joined by broadcast, so a hub costs no task its memory or time.  State is cut by
reliable checkpoints, as a lost executor must not undo the loop; a round's state goes when the next one's is kept.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelgrid.plans.state import released, settled


#: a vertex with more than this share of all rows is a hub; there are fewer than 2000 of them
HUB_SHARE = 1000


def _told(rows: DataFrame, least: DataFrame, most: int) -> DataFrame:
    """`rows` (u, v) with m of `least` (u, m, n); hubs, with more than `most` rows, meet theirs by broadcast and not in one task."""
    hubs = F.broadcast(least.where(F.col("n") > most).select("u", "m"))
    others = least.where(F.col("n") <= most).select("u", "m")
    return rows.join(hubs, "u").unionAll(rows.join(hubs, "u", "left_anti").join(others, "u"))


def _large_star(edges: DataFrame, most: int) -> DataFrame:
    both = edges.unionAll(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n")).select("u", F.least("u", "m").alias("m"), "n")
    return _told(both.where("v > u"), least, most).select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")


def _small_star(edges: DataFrame, most: int) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = down.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n"))
    moved = _told(down, least, most).select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.unionAll(least.select("u", F.col("m").alias("v"))).where("u <> v").distinct()


def _is_stars(edges: DataFrame) -> bool:
    """Whether every vertex hangs on one other that hangs on none."""
    twice = edges.groupBy("u").agg(F.count("*").alias("n")).where("n > 1").select("u")
    inner = edges.select("u").join(edges.select(F.col("v").alias("u")), "u", "left_semi")
    return twice.unionAll(inner).isEmpty()


def star_components(edges: DataFrame, max_rounds: int = 50, rows: int | None = None) -> DataFrame:
    """(v, component) for every vertex of `edges` (u, v): the component is its smallest vertex.

    Vertices without edges to others are not returned; self-loops and repeated edges don't matter.
    `rows`, if known, bounds the number of different edges.
    """
    now = settled(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), rows)
    most = (now.count() if rows is None else rows) // HUB_SHARE
    for _ in range(max_rounds):
        if _is_stars(now):
            roots = now.select("v", F.col("v").alias("component")).distinct()
            return now.select(F.col("u").alias("v"), F.col("v").alias("component")).unionAll(roots)
        before, now = now, settled(_small_star(_large_star(now, most), most), rows)
        released(before)
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
