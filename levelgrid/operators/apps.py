"""What searches are used for: components, two-colouring, eccentricity and diameter bounds, flow."""

from __future__ import annotations

from collections import deque

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelgrid.operators.components import star_components
from levelgrid.operators.levels import bfs_batched, bfs_levels


def components(edges: DataFrame) -> DataFrame:
    """(v, component) of every vertex with an edge: the smallest vertex that it is joined to."""
    return star_components(edges.select(F.col("src").alias("u"), F.col("dst").alias("v")))


def odd_edges(graph: DataFrame, levels: DataFrame) -> int:
    """Edges between vertices of equal level parity: a component is bipartite if and only if it has none."""
    parity = levels.select("v", (F.col("level") % 2).alias("p"))
    ends = graph.join(parity.select(F.col("v").alias("src"), F.col("p").alias("a")), "src").join(parity.select(F.col("v").alias("dst"), F.col("p").alias("b")), "dst")
    return ends.where("a = b and src < dst").count()


def is_bipartite(graph: DataFrame, root: int) -> bool:
    """Whether the root's component is bipartite."""
    return odd_edges(graph, bfs_levels(graph, root)) == 0


def eccentricities(graph: DataFrame, roots: DataFrame) -> DataFrame:
    """(root, eccentricity) within each root's component."""
    return bfs_batched(graph, roots).groupBy("root").agg(F.max("level").alias("eccentricity"))


def diameter_bounds(graph: DataFrame, root: int) -> tuple[int, int]:
    """(lower, upper) bounds of the component's diameter by two sweeps: from the root, then from a farthest vertex."""
    first = bfs_levels(graph, root)
    row = first.agg(F.max(F.struct("level", (-F.col("v")).alias("w"))).alias("far")).first()["far"]
    second = bfs_levels(graph, -row["w"]).agg(F.max("level").alias("n")).first()["n"]
    return max(row["level"], second), 2 * min(row["level"], second)


def max_flow(edges: DataFrame, source: int, sink: int, largest: int = 100_000) -> int:
    """Maximum flow of unit-capacity directed edges by shortest augmenting paths; for graphs of at most `largest` edges.

    Augmenting is sequential, so a graph within the bound is searched on the driver; a larger one is refused.
    """
    rows = edges.select("src", "dst").limit(largest + 1).collect()
    if len(rows) > largest:
        raise ValueError(f"max_flow takes at most {largest} edges")
    room: dict[int, dict[int, int]] = {}
    for u, v in rows:
        if u != v:
            room.setdefault(u, {}).setdefault(v, 0)
            room[u][v] += 1
            room.setdefault(v, {}).setdefault(u, 0)
    flow = 0
    while True:
        parent, queue = {source: source}, deque([source])
        while queue and sink not in parent:
            u = queue.popleft()
            for v, left in room.get(u, {}).items():
                if left > 0 and v not in parent:
                    parent[v] = u
                    queue.append(v)
        if sink not in parent or source == sink:
            return flow
        v = sink
        while v != source:
            u = parent[v]
            room[u][v] -= 1
            room[v][u] += 1
            v = u
        flow += 1
