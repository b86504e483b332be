"""The engine in a few chained calls.

    GraphSearch(spark).from_edges(edges, n).grid(4, 4).bfs(root).levels()
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levelgrid.functions.grid import GridSpec
from levelgrid.operators import levels as plain
from levelgrid.operators import measures, prepare
from levelgrid.operators.search import Search, search
from levelgrid.plans.layout import GridLayout, Layout, ModuloLayout, PlacedGraph, build
from levelgrid.plans.state import settled
from levelgrid.sources.graphs import require_edge_schema, rmat_edges


@dataclass(frozen=True)
class GraphSearch:
    spark: SparkSession
    edges: DataFrame | None = None
    graph: DataFrame | None = None
    n: int = 0
    placed: PlacedGraph | None = None

    def from_edges(self, edges: DataFrame, n: int | None = None) -> GraphSearch:
        """Input tuples (src, dst); ids are checked to lie in [0, n)."""
        edges = require_edge_schema(edges)
        row = edges.agg(F.min(F.least("src", "dst")).alias("low"), F.max(F.greatest("src", "dst")).alias("high")).first()
        size = n if n is not None else (row["high"] if row["high"] is not None else 0) + 1
        if row["low"] is not None and (row["low"] < 0 or row["high"] >= size):
            raise ValueError(f"ids run from {row['low']} to {row['high']}, outside 0 to {size - 1}")
        return replace(self, edges=edges, graph=settled(prepare.symmetrize(edges)), n=size, placed=None)

    def generated(self, scale: int, edge_factor: int = 16, seed: int = 42) -> GraphSearch:
        return self.from_edges(rmat_edges(self.spark, scale, edge_factor, seed=seed), 1 << scale)

    def _laid(self, layout: Layout, chunk: int) -> GraphSearch:
        if self.graph is None:
            raise ValueError("no edges yet")
        return replace(self, placed=build(self.graph, layout, chunk))

    def grid(self, r: int, c: int, chunk: int = 4096) -> GraphSearch:
        return self._laid(GridLayout(GridSpec(self.n, r, c)), chunk)

    def modulo(self, p: int, chunk: int = 4096) -> GraphSearch:
        return self._laid(ModuloLayout(p, self.n), chunk)

    def bfs(self, root: int, **options) -> Search:
        """A distributed search; without a layout, on one cell."""
        if not 0 <= root < self.n:
            raise ValueError(f"root {root} is outside 0 to {self.n - 1}")
        return search((self if self.placed else self.grid(1, 1)).placed, root, **options)

    def levels(self, root: int, max_level: int | None = None) -> DataFrame:
        """The plain form, for graphs that need no placement."""
        return plain.bfs_levels(self.graph, root, max_level)

    def tuples_traversed(self, levels: DataFrame) -> int:
        return measures.tuples_traversed(self.edges, levels)
