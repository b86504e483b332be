"""Where edges and vertices live: the two-dimensional grid, and the one-dimensional modulo rule.

A layout builds the placed adjacency once: rows (cell, key, part, targets) with the targets of one vertex
in chunks, so that a hub is many rows.  The rows are put on the cell's task, sorted by key and checkpointed; with
adaptive planning off (`PLACED`) later joins, unions and aggregations on the cell find them in place and in order,
so edges are never moved or sorted again: a level moves only frontiers and found vertices.

Spark knows a placement by hash through joins, unions and aggregations.  To have each cell on a task of its own all
the same, cells are named by seats inside the frames: the seat of cell i of p is a number that hashes to i
modulo p, so the cell of a seat is computed, and the seat of a cell is looked up in a list of p numbers.

Above the checkpoint the adjacency is held as columns, in batches of a few MB that know their smallest and
largest key (memory first, then disk; a lost batch is made again from the checkpoint).  A level asks for the
stretches of keys that its frontier touches (`touched`), and batches outside are not read.
"""

from __future__ import annotations

import functools
import itertools
from dataclasses import dataclass

import numpy as np
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F

from levelgrid.functions.grid import GridSpec
from levelgrid.plans.state import held, released, settled

#: inside a build or a search: keep placements, and never re-plan by broadcasting what grows
PLACED = {
    "spark.sql.adaptive.enabled": "false",
    "spark.sql.autoBroadcastJoinThreshold": "-1",
    "spark.sql.requireAllClusterKeysForCoPartition": "false",
    "spark.sql.requireAllClusterKeysForDistribution": "false",
}

#: inside a build: lists are collected from sorted rows, not in a map of buffers that overflows and is sorted then
IN_ORDER = {"spark.sql.execution.useObjectHashAggregateExec": "false"}


def hash_of(number: int, seed: int = 42) -> int:
    """Spark's hash of an int (Murmur3, 32 bits)."""
    mask = 0xFFFFFFFF
    turned = lambda x, n: (x << n | x >> 32 - n) & mask
    k = turned(number * 0xCC9E2D51 & mask, 15) * 0x1B873593 & mask
    h = (turned(seed ^ k, 13) * 5 + 0xE6546B64 & mask) ^ 4
    h = (h ^ h >> 16) * 0x85EBCA6B & mask
    h = (h ^ h >> 13) * 0xC2B2AE35 & mask
    h ^= h >> 16
    return h - (1 << 32) if h >> 31 else h


@functools.lru_cache(maxsize=64)
def seats(cells: int) -> tuple[int, ...]:
    """For each cell the smallest number that hashes to it modulo their number."""
    found: dict[int, int] = {}
    for number in itertools.count():
        found.setdefault(hash_of(number) % cells, number)
        if len(found) == cells:
            return tuple(found[i] for i in range(cells))


class Layout:
    """What a search needs to know; `value` is how a cell names a target, `key` how it names a source; cells stand as seats."""

    cells: int
    name: str
    #: whether a cell has others to send to in each phase
    expands: bool = False
    folds: bool = True

    def seat(self, number: Column) -> Column:
        return F.get(F.expr(f"array({', '.join(map(str, seats(self.cells)))})"), number.cast("int"))

    def number(self, cell: Column) -> Column:
        """The cell's number, from its seat."""
        return F.pmod(F.hash(cell), F.lit(self.cells)).cast("int")

    @property
    def nb(self) -> int:
        """Vertices of a block: the places of a packed message."""
        raise NotImplementedError

    def index(self, value: Column) -> Column:
        """Place of a target in its owner's block, as a message tells it."""
        ...

    def value_from(self, owner: Column, index: Column) -> Column: ...
    def key_index(self, key: Column) -> Column:
        """Place of a frontier vertex in its owner's block."""
        ...

    def key_from(self, sender: Column, index: Column) -> Column: ...

    def place(self, graph: DataFrame) -> DataFrame:
        """(cell, key, value) for (src, dst); here cells are numbers."""
        raise NotImplementedError

    def root(self, v: Column) -> dict[str, Column]:
        """cell, key and value of a vertex at its owner."""
        return {"cell": self.seat(self.owner(v)), "key": self.key_of(v), "value": self.value_of(v)}

    def owner(self, v: Column) -> Column:
        """Number of the cell that owns a vertex."""
        ...

    def key_of(self, v: Column) -> Column: ...
    def value_of(self, v: Column) -> Column: ...
    def expand_cells(self, cell: Column) -> Column:
        """All cells that hold edges of an owned vertex, as an array."""
        ...

    def owner_of_value(self, cell: Column, value: Column) -> Column: ...
    def key_at_owner(self, owner: Column, value: Column) -> Column: ...
    def vertex(self, owner: Column, value: Column) -> Column: ...
    def sender(self, cell: Column) -> Column:
        """How a receiver remembers the sender."""
        ...

    def sender_cell(self, owner: Column, sender: Column) -> Column: ...
    def source(self, cell: Column, key: Column) -> Column:
        """Global id of a source in a cell."""
        ...


@dataclass
class GridLayout(Layout):
    grid: GridSpec

    def __post_init__(self):
        g = self.grid
        self.cells, self.name = g.cells, f"grid {g.r}x{g.c}"
        self.expands, self.folds = g.r > 1, g.c > 1

    def _row(self, cell):
        return F.floor(self.number(cell) / self.grid.c).cast("int")

    def _column(self, cell):
        return self.number(cell) % self.grid.c

    @property
    def nb(self):
        return self.grid.nb

    def index(self, value):
        return value % self.nb

    def value_from(self, owner, index):
        return (self._column(owner) * self.nb + index).cast("int")

    def key_index(self, key):
        return key % self.nb

    def key_from(self, sender, index):
        return (self._row(sender) * self.nb + index).cast("int")

    def place(self, graph):
        g = self.grid
        return graph.select(g.edge_cell(F.col("src"), F.col("dst")).alias("cell"), g.local_column(F.col("src")).alias("key"), g.local_row(F.col("dst")).alias("value"))

    def owner(self, v):
        return self.grid.owner_cell(v)

    def key_of(self, v):
        return self.grid.local_column(v)

    def value_of(self, v):
        return self.grid.local_row(v)

    def expand_cells(self, cell):
        g, column = self.grid, self._column(cell)
        return F.transform(F.sequence(F.lit(0), F.lit(g.r - 1)), lambda i: self.seat(i * g.c + column))

    def owner_of_value(self, cell, value):
        return self.seat(self._row(cell) * self.grid.c + self.grid.column_of_row(value))

    def key_at_owner(self, owner, value):
        return self.grid.row_to_column(self._row(owner), value)

    def vertex(self, owner, value):
        return self.grid.global_row(self._row(owner), value)

    def sender(self, cell):
        return self._column(cell).cast("int")

    def sender_cell(self, owner, sender):
        return self.seat(self._row(owner) * self.grid.c + sender)

    def source(self, cell, key):
        return self.grid.global_column(self._column(cell), key)


@dataclass
class ModuloLayout(Layout):
    """The earlier rule: vertex v and its whole out-list belong to cell v mod p; keys and values are global ids."""

    p: int
    #: vertices; packed messages need it
    n: int | None = None

    def __post_init__(self):
        self.cells, self.name, self.folds = self.p, f"modulo {self.p}", self.p > 1

    @property
    def nb(self):
        if self.n is None:
            raise ValueError("packed messages need the number of vertices: ModuloLayout(p, n)")
        return -(-self.n // self.p)

    def index(self, value):
        return F.floor(value / self.p).cast("long")

    def value_from(self, owner, index):
        return index.cast("long") * self.p + self.number(owner)

    def key_index(self, key):
        return self.index(key)

    def key_from(self, sender, index):
        return self.value_from(sender, index)

    def place(self, graph):
        return graph.select((F.col("src") % self.p).cast("int").alias("cell"), F.col("src").alias("key"), F.col("dst").alias("value"))

    def owner(self, v):
        return (v % self.p).cast("int")

    def key_of(self, v):
        return v

    def value_of(self, v):
        return v

    def expand_cells(self, cell):
        return F.array(cell)

    def owner_of_value(self, cell, value):
        return self.seat(value % self.p)

    def key_at_owner(self, owner, value):
        return value

    def vertex(self, owner, value):
        return value

    def sender(self, cell):
        return self.number(cell)

    def sender_cell(self, owner, sender):
        return self.seat(sender)

    def source(self, cell, key):
        return key


def chunked(placed: DataFrame, *cell: str, chunk: int = 4096) -> DataFrame:
    """(cell, key, part, targets): sorted targets of each source in a cell, at most `chunk` a row, no values."""
    # key before cell: sorts compare their first column cheaply, and a task may hold few cells
    nth = F.row_number().over(Window.partitionBy("key", *cell).orderBy("value")) - 1
    parts = placed.withColumn("part", F.floor(nth / chunk).cast("int"))
    return parts.groupBy("key", *cell, "part").agg(F.sort_array(F.collect_list("value")).alias("targets")).select(*cell, "key", "part", "targets")


def compressed(placed: DataFrame, *cell: str, chunk: int = 4096) -> DataFrame:
    """Chunks of targets in order of key, in the tasks where the edges are."""
    return chunked(placed, *cell, chunk=chunk).sortWithinPartitions(*cell, "key", "part")


#: the key space of a cell is watched in so many equal blocks, the bits of one bitmap
KEY_BLOCKS = 1 << 15
#: a scan asks for at most so many stretches of keys; the narrowest gaps are read as well
STRETCHES = 8
#: rows that Spark puts in one batch of columns: fewer keys have nothing to leave out
BATCH_ROWS = 10_000


@dataclass
class PlacedGraph:
    layout: Layout | None
    adjacency: DataFrame
    #: keys that occur lie in [0, keys)
    keys: int
    tasks: int

    @property
    def key_block(self) -> int:
        return max(1, -(-self.keys // KEY_BLOCKS))

    def watched(self, key: Column) -> Column:
        """An aggregate, 4 KiB at most, that tells which blocks of the key space occur; null keys don't count."""
        return F.bitmap_construct_agg(F.floor(key / self.key_block).cast("long"))

    def touched(self, bits: bytes | None, least: int = BATCH_ROWS) -> DataFrame:
        """The adjacency of the keys in the blocks of a bitmap, and of some between them; all of it for None or if there are few keys."""
        if bits is None or self.keys <= least:
            return self.adjacency
        blocks = np.flatnonzero(np.unpackbits(np.frombuffer(bits, dtype=np.uint8), bitorder="little"))
        size = self.key_block
        some = [f"key between {a * size} and {(b + 1) * size - 1}" for a, b in stretches(blocks.tolist())]
        return self.adjacency.where(" or ".join(some) or "false")

    def close(self) -> None:
        """Gives the storage back; the graph can't be searched any more."""
        self.adjacency.unpersist()
        released(self.adjacency)


def stretches(blocks: list[int], most: int = STRETCHES) -> list[tuple[int, int]]:
    """Runs (first, last) that cover the ascending blocks, at most `most`; the widest gaps are left out."""
    if not blocks:
        return []
    gaps = sorted(((b - a, a, b) for a, b in zip(blocks, blocks[1:]) if b - a > 1), reverse=True)[: most - 1]
    cuts = sorted((a, b) for _, a, b in gaps)
    return list(zip([blocks[0], *(b for _, b in cuts)], [*(a for a, _ in cuts), blocks[-1]]))


def either(*bits: bytes) -> bytes:
    """The blocks of any of some bitmaps."""
    return np.bitwise_or.reduce([np.frombuffer(x, dtype=np.uint8) for x in bits]).tobytes()


def held_in_place(rows: DataFrame, layout: Layout | None, tasks: int) -> PlacedGraph:
    """Placed and ordered rows (.., key, ..) in reliable storage, and above it as columns."""
    seen = Observation()
    rows = settled(rows.observe(seen, F.max("key").alias("last")))
    last = seen.get["last"]
    return PlacedGraph(layout, rows.persist(StorageLevel.MEMORY_AND_DISK), 0 if last is None else last + 1, tasks)


def build(graph: DataFrame, layout: Layout, chunk: int = 4096) -> PlacedGraph:
    """Two shuffles: all edges (src, dst) by source and cell, where all tasks make chunks of them; the chunks to their cells, sorted and checkpointed in place."""
    with held(graph.sparkSession, PLACED | IN_ORDER):
        placed = layout.place(graph).withColumn("cell", layout.seat(F.col("cell")))
        # a cell is one task and there may be fewer cells than cores: the task only puts finished chunks in order
        chunks = chunked(placed.repartition("key", "cell"), "cell", chunk=chunk).repartition(layout.cells, "cell")
        return held_in_place(chunks.sortWithinPartitions("cell", "key", "part"), layout, layout.cells)


def grid_property_violations(graph: DataFrame, grid: GridSpec) -> DataFrame:
    """(property, violations): lists of a vertex outside its owner's grid column; targets owned outside the edge's grid row."""
    cell = grid.edge_cell(F.col("src"), F.col("dst"))
    told = graph.select(
        (cell % grid.c != grid.owner_column(F.col("src"))).cast("long").alias("column"),
        (F.floor(cell / grid.c) != grid.owner_row(F.col("dst"))).cast("long").alias("row"),
    )
    sums = told.agg(F.coalesce(F.sum("column"), F.lit(0)).alias("column"), F.coalesce(F.sum("row"), F.lit(0)).alias("row"))
    return sums.select(F.expr("stack(2, 'list in grid column', `column`, 'owner in grid row', `row`) as (property, violations)"))


def load_balance(graph: DataFrame, layout: Layout) -> DataFrame:
    """(cell, edges, sources) of every cell that has edges."""
    return layout.place(graph).groupBy("cell").agg(F.count("*").alias("edges"), F.count_distinct("key").alias("sources"))
