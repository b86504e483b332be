"""Arithmetic of the two-dimensional grid of cells, as Column expressions and as SQL functions.

N vertices are cut into R*C blocks of `nb` consecutive ids; the last ones may be short or empty.  Cell
(i, j) owns block j*R + i.  The edge u -> v lies in grid row (v div nb) mod R and grid column
u div (nb*R), so that the out-lists of a column's vertices stay in that column and the owner of a target
is in the row of the edge.  Cells are numbered i*C + j.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def _div(a: Column, b: int) -> Column:
    return F.floor(a / F.lit(b)) if b & (b - 1) else F.shiftright(a, b.bit_length() - 1)


@dataclass(frozen=True)
class GridSpec:
    n: int
    r: int
    c: int

    def __post_init__(self):
        if min(self.n, self.r, self.c) < 1:
            raise ValueError("a grid needs at least one vertex, one row and one column")
        if max(self.rows, self.columns) >= 1 << 31:
            raise ValueError("local ids must fit 32 bits: use more cells")

    @property
    def cells(self) -> int:
        return self.r * self.c

    @property
    def nb(self) -> int:
        """Vertices of a block."""
        return -(-self.n // self.cells)

    @property
    def rows(self) -> int:
        """Rows of a cell's local matrix."""
        return self.nb * self.c

    @property
    def columns(self) -> int:
        """Columns of a cell's local matrix."""
        return self.nb * self.r

    def block(self, v: Column) -> Column:
        return _div(v, self.nb)

    def owner_row(self, v: Column) -> Column:
        return (self.block(v) % self.r).cast("int")

    def owner_column(self, v: Column) -> Column:
        return _div(v, self.nb * self.r).cast("int")

    def owner_cell(self, v: Column) -> Column:
        return (self.owner_row(v) * self.c + self.owner_column(v)).cast("int")

    def edge_cell(self, u: Column, v: Column) -> Column:
        return (self.owner_row(v) * self.c + self.owner_column(u)).cast("int")

    def local_column(self, u: Column) -> Column:
        return (u % (self.nb * self.r)).cast("int")

    def local_row(self, v: Column) -> Column:
        return (self.owner_column(v) * self.nb + v % self.nb).cast("int")

    def row_to_column(self, row: Column, lrow: Column) -> Column:
        """The local column of an owned vertex from its local row."""
        return (row * self.nb + lrow % self.nb).cast("int")

    def column_of_row(self, lrow: Column) -> Column:
        """The grid column that owns a local row."""
        return _div(lrow, self.nb).cast("int")

    def global_row(self, row: Column, lrow: Column) -> Column:
        return (self.column_of_row(lrow).cast("long") * self.r + row) * self.nb + lrow % self.nb

    def global_column(self, column: Column, lcol: Column) -> Column:
        return column.cast("long") * (self.nb * self.r) + lcol

    def memory(self) -> dict[str, int]:
        """Words of a cell's fixed arrays: column offsets, bitmap, level and parent, and a full frontier."""
        return {"offsets": self.columns + 1, "bitmap_words": -(-self.rows // 32), "level_words": self.rows, "parent_words": self.rows, "frontier_words": self.nb}


def register_sql(spark: SparkSession) -> None:
    """SQL functions with inlined bodies: grid_cell(u, v, n, r, c) and owner_cell(v, n, r, c)."""
    nb = "CAST(ceil(n / CAST(r * c AS DOUBLE)) AS BIGINT)"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION owner_cell(v BIGINT, n BIGINT, r BIGINT, c BIGINT) RETURNS BIGINT RETURN (v div {nb}) % r * c + v div ({nb} * r)")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION grid_cell(u BIGINT, v BIGINT, n BIGINT, r BIGINT, c BIGINT) RETURNS BIGINT RETURN (v div {nb}) % r * c + u div ({nb} * r)")
