"""The distributed search over a placed graph: expand, frontier expansion, local split, fold, update.

One loop serves the grid and the modulo layout, and all variants:

* `dedup`: 'receiver' sends every edge and the owner keeps one; 'level' sends a vertex once a level and
  cell; 'history' sends it once in the whole search, since a cell remembers all it has found;
* `once`: how a cell keeps one edge of many, 'atomic' (hash minimum) or 'compact' (sort, number, filter);
* `parents`: 'late' folds vertices only and asks the sender for the parent at the end; 'eager' sends it;
* `rule`: 'owner_first' prefers the parent that the owner itself found, else that of the first sender;
  'smallest' takes the smallest parent of all (it needs eager parents and no memory of earlier levels);
* `codec`: None moves rows; 'list', 'bitmap' or 'auto' moves packed messages in both exchanges;
* `kernel`: 'sql' expands by join and explode, 'arrow' by a scan and binary search for each cell, a group of
  `group` edges for each search;
* `state`: 'set' tests membership against rows, 'bits' against the packed bitmap of all a cell has reached.

A level reads the stretches of the sorted adjacency that its frontier touches, in place, and moves frontiers and
foreign vertices only: vertices that the discovering cell owns join the new frontier without an exchange.
Membership tests are one aggregation with what is known, which lies in place.  As a set, what must be known does not
grow: in an undirected graph a cell finds a vertex again at most two levels after it found it first, so two slices
of what was found and received answer all tests.  As bits, it is one bit a row and cell.

Inside the frames a cell stands as its seat (`plans.layout`); messages name cells by number.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F

from levelgrid.operators import codec as packing
from levelgrid.operators.kernel import expand_cells
from levelgrid.plans.layout import PLACED, Layout, PlacedGraph, either
from levelgrid.plans.state import held, released, settled

#: slices of one kind are gathered in one frame when there are so many
SLICES = 32


@dataclass
class Search:
    """What a search leaves: fronts and found vertices by level, and the seconds of each phase."""

    graph: PlacedGraph
    root: int
    dedup: str
    late: bool
    codec: str | None = None
    fronts: list[DataFrame] = field(default_factory=list)  # (cell, key, value, sender, u, level)
    found: list[DataFrame] = field(default_factory=list)  # (cell, value, key, owner, level)
    seconds: list[tuple[int, str, float]] = field(default_factory=list)

    def _all(self, slices: list[DataFrame]) -> DataFrame:
        return reduce(DataFrame.unionAll, slices)

    def _gather(self, recent: int = 8) -> None:
        """Older slices become one, so that the plan does not grow with the number of levels."""
        for slices in (self.fronts, self.found):
            if len(slices) >= SLICES + recent:
                slices[:-recent] = [settled(self._all(slices[:-recent]))]

    def levels(self) -> DataFrame:
        """(v, level)."""
        fronts = self._all(self.fronts)
        return fronts.select(self.graph.layout.vertex(F.col("cell"), F.col("value")).alias("v"), "level")

    def tree(self) -> DataFrame:
        """(v, level, pred): late parents are asked for at the recorded sender, one exchange of visited vertices."""
        layout = self.graph.layout
        fronts = self._all(self.fronts)
        v = layout.vertex(F.col("cell"), F.col("value")).alias("v")
        start = fronts.where("level = 0").select(v, "level", F.lit(self.root).cast("long").alias("pred"))
        later = fronts.where("level > 0")
        if not self.late:
            return start.unionAll(later.select(v, "level", F.col("u").alias("pred")))
        asked = later.select(v, "level", layout.sender_cell(F.col("cell"), F.col("sender")).alias("at"), F.col("value").alias("of"))
        kept = self._all(self.found).groupBy("cell", "value", F.col("level").alias("found_at")).agg(F.min("key").alias("key"))
        told = asked.join(kept, (F.col("at") == F.col("cell")) & (F.col("of") == F.col("value")) & (F.col("level") == F.col("found_at")))
        return start.unionAll(told.select("v", "level", layout.source(F.col("cell"), F.col("key")).alias("pred")))

    def expand_messages(self) -> DataFrame:
        """(level, sender, receiver, vertices) of the expand exchanges; the frontier of level L is sent in round L + 1."""
        layout = self.graph.layout
        fronts = self._all(self.fronts).groupBy("level", "cell").agg(F.count("*").alias("vertices"))
        sent = fronts.select((F.col("level") + 1).alias("level"), F.col("cell").alias("from"), F.explode(layout.expand_cells(F.col("cell"))).alias("to"), "vertices").where("from <> to")
        return sent.select("level", layout.number(F.col("from")).alias("sender"), layout.number(F.col("to")).alias("receiver"), "vertices")

    def fold_messages(self) -> DataFrame:
        """(level, sender, receiver, vertices) of the fold exchanges: vertices, or edges when nothing is removed before."""
        number = self.graph.layout.number
        sent = self._all(self.found).where("cell <> owner").groupBy("level", "cell", "owner").agg(F.count("*").alias("vertices"))
        return sent.select("level", number(F.col("cell")).alias("sender"), number(F.col("owner")).alias("receiver"), "vertices")

    def sent_messages(self) -> DataFrame:
        """(phase, level, sender, receiver, kind, vertices, bytes) of packed messages as they were sent; bytes are those of the lists and bitmaps themselves."""
        if self.codec is None:
            raise ValueError("this search moved rows, not packed messages")
        layout = self.graph.layout
        fold = packing.messages(fold_rows(self._all(self.found), layout, "level"), ["level", "cell", "to"], "index", layout.nb, self.codec)
        fold = fold.select(F.lit("fold").alias("phase"), "level", F.col("cell").alias("from"), "to", "kind", "n", packing.payload().alias("bytes"))
        front = self._all(self.fronts).select((F.col("level") + 1).alias("level"), "cell", layout.key_index(F.col("key")).alias("index"))
        expand = packing.messages(front, ["level", "cell"], "index", layout.nb, self.codec)
        expand = expand.select(F.lit("expand").alias("phase"), "level", F.col("cell").alias("from"), F.explode(layout.expand_cells(F.col("cell"))).alias("to"), "kind", "n", packing.payload().alias("bytes")).where("from <> to")
        told = fold.unionAll(expand).groupBy("phase", "level", "from", "to", "kind").agg(F.max("n").alias("vertices"), F.sum("bytes").alias("bytes"))
        return told.select("phase", "level", layout.number(F.col("from")).alias("sender"), layout.number(F.col("to")).alias("receiver"), "kind", "vertices", "bytes")

    def phases(self) -> DataFrame:
        return self.graph.adjacency.sparkSession.createDataFrame(self.seconds, "level int, phase string, seconds double")


def _once(scanned: DataFrame, known: list[DataFrame], once: str) -> DataFrame:
    """(cell, value, key): one edge for each found vertex, the one with the smallest key, without known vertices."""
    rows = scanned.select("cell", "value", "key", F.lit(0).alias("old"))
    key = rows.schema["key"].dataType
    for slice_ in known:
        rows = rows.unionAll(slice_.select("cell", "value", F.lit(None).cast(key).alias("key"), F.lit(1).alias("old")))
    if once == "atomic":
        return rows.groupBy("cell", "value").agg(F.min("key").alias("key"), F.max("old").alias("old")).where("old = 0").drop("old")
    if once == "compact":
        nth = F.row_number().over(Window.partitionBy("cell", "value").orderBy(F.desc("old"), "key"))
        return rows.withColumn("nth", nth).where("nth = 1 and old = 0").drop("nth", "old")
    raise ValueError(f"once is 'atomic' or 'compact', not {once!r}")


def _without(found: DataFrame, *known: DataFrame) -> DataFrame:
    columns = found.columns
    for slice_ in known:
        found = found.join(slice_.select("cell", "value").hint("merge"), ["cell", "value"], "left_anti")
    return found.select(*columns)


class Reached:
    """The packed bitmap of all that a cell has reached, its own and foreign rows alike: (cell, word, bits) of words with a bit set, in place."""

    def __init__(self):
        self.state: DataFrame | None = None

    def add(self, *more: DataFrame) -> None:
        rows = [x.select("cell", packing.word(F.col("value")).alias("word"), packing.bit(F.col("value")).alias("bits")) for x in more]
        before = self.state
        rows += [] if before is None else [before]
        self.state = settled(reduce(DataFrame.unionAll, rows).groupBy("cell", "word").agg(F.bit_or("bits").alias("bits")).sortWithinPartitions("cell", "word"))
        if before is not None:
            released(before)

    def without(self, found: DataFrame) -> DataFrame:
        told = found.withColumn("word", packing.word(F.col("value"))).join(self.state.hint("merge"), ["cell", "word"], "left")
        return told.where(F.col("bits").isNull() | ~packing.bit_set(F.col("bits"), F.col("value"))).select(*found.columns)


def expanded(front: DataFrame, graph: PlacedGraph, codec: str | None) -> DataFrame:
    """(cell, key) of the frontier at all cells that hold edges of it: one exchange, none where a cell has no others to send to."""
    layout = graph.layout
    if not layout.expands:
        return front.select("cell", "key")
    if codec is None:
        return front.select(F.explode(layout.expand_cells(F.col("cell"))).alias("cell"), "key").repartition(layout.cells, "cell")
    sent = packing.messages(front.select("cell", layout.key_index(F.col("key")).alias("index")), ["cell"], "index", layout.nb, codec)
    sent = sent.withColumnRenamed("cell", "from").withColumn("cell", F.explode(layout.expand_cells(F.col("from")))).repartition(layout.cells, "cell")
    told = packing.unpack(sent, ["cell", "from"], "index")
    return told.select("cell", layout.key_from(F.col("from"), F.col("index")).alias("key"))


def fold_rows(found: DataFrame, layout: Layout, *also: str) -> DataFrame:
    """(also, cell, to, index): foreign vertices by their place in the owner's block."""
    return found.where("cell <> owner").select(*also, "cell", F.col("owner").alias("to"), layout.index(F.col("value")).alias("index"))


def folded(found: DataFrame, graph: PlacedGraph, codec: str | None, late: bool) -> DataFrame:
    """(cell, value, sender, u) of foreign vertices at their owners: one exchange."""
    layout, nothing = graph.layout, F.lit(None).cast("long").alias("u")
    if codec is None:
        sent = found.where("cell <> owner").select(
            F.col("owner").alias("cell"), "value", layout.sender(F.col("cell")).alias("sender"), nothing if late else layout.source(F.col("cell"), F.col("key")).alias("u")
        )
        return sent.repartition(layout.cells, "cell")
    sent = packing.messages(fold_rows(found, layout), ["cell", "to"], "index", layout.nb, codec)
    sent = sent.select(F.col("to").alias("cell"), layout.sender(F.col("cell")).alias("sender"), "bucket", "kind", "idx", "words").repartition(layout.cells, "cell")
    told = packing.unpack(sent, ["cell", "sender"], "index")
    return told.select("cell", layout.value_from(F.col("cell"), F.col("index")).alias("value"), "sender", nothing)


def _fresh(sent: DataFrame, known: list[DataFrame], late: bool) -> DataFrame:
    """(cell, value, sender, u): of each received vertex that is not known, the first sender and its smallest parent."""
    rows = sent.select("cell", "value", "sender", "u", F.lit(0).alias("old"))
    for slice_ in known:
        rows = rows.unionAll(slice_.select("cell", "value", F.lit(None).cast("int").alias("sender"), F.lit(None).cast("long").alias("u"), F.lit(1).alias("old")))
    if late:
        told = rows.groupBy("cell", "value").agg(F.min("sender").alias("sender"), F.max("old").alias("old"))
        return told.where("old = 0").select("cell", "value", "sender", F.lit(None).cast("long").alias("u"))
    told = rows.groupBy("cell", "value", "sender").agg(F.min("u").alias("u"), F.max("old").alias("old"))
    told = told.groupBy("cell", "value").agg(F.min(F.when(F.col("old") == 0, F.struct("sender", "u"))).alias("best"), F.max("old").alias("old"))
    return told.where("old = 0").select("cell", "value", "best.sender", "best.u")


def _smallest(own: DataFrame, sent: DataFrame, known: list[DataFrame]) -> DataFrame:
    """(cell, value, sender, u): of each vertex that is not known, the smallest parent, whoever found it."""
    rows = reduce(DataFrame.unionAll, [x.select("cell", "value", F.struct("u", "sender").alias("best"), F.lit(0).alias("old")) for x in (own, sent)])
    for slice_ in known:
        rows = rows.unionAll(slice_.select("cell", "value", F.lit(None).cast(rows.schema["best"].dataType).alias("best"), F.lit(1).alias("old")))
    told = rows.groupBy("cell", "value").agg(F.min("best").alias("best"), F.max("old").alias("old"))
    return told.where("old = 0").select("cell", "value", "best.sender", "best.u")


def search(
    graph: PlacedGraph,
    root: int,
    dedup: str = "history",
    parents: str = "late",
    rule: str = "owner_first",
    once: str = "atomic",
    codec: str | None = None,
    kernel: str = "sql",
    group: int = 1,
    state: str = "set",
    max_level: int | None = None,
    profile: bool = False,
) -> Search:
    """Searches from `root`; with `profile` each phase is materialised and timed by itself."""
    if dedup not in ("receiver", "level", "history") or parents not in ("late", "eager") or rule not in ("owner_first", "smallest") or state not in ("set", "bits") or kernel not in ("sql", "arrow"):
        raise ValueError("unknown variant")
    if rule == "smallest" and (parents == "late" or dedup == "history"):
        raise ValueError("the smallest parent needs eager parents and all senders of a level")
    if codec and parents == "eager":
        raise ValueError("packed messages carry vertices only")
    if codec and dedup == "receiver":
        raise ValueError("packed messages carry a vertex once: remove repeats before they are sent")
    if state == "bits" and dedup != "history":
        raise ValueError("the bitmap of a cell is its history")
    layout, spark, late = graph.layout, graph.adjacency.sparkSession, parents == "late"
    if codec:
        layout.nb  # noqa: B018 - says what is missing
    out = Search(graph, root, dedup, late, codec)
    clock = 0.0

    def passed(level: int, phase: str, frame: DataFrame | None = None) -> DataFrame | None:
        """Ends a phase; a frame that is not kept yet is."""
        nonlocal clock
        if profile:
            frame = frame if frame is None else settled(frame)
            out.seconds.append((level, phase, time.perf_counter() - clock))
            clock = time.perf_counter()
        return frame

    def watched(frame: DataFrame, new: Column) -> tuple[DataFrame, int, bytes]:
        """The frame in reliable storage, how many keys it adds to the frontier, and the blocks of the key space that they are in."""
        seen = Observation()
        frame = settled(frame.observe(seen, F.count(new).alias("n"), graph.watched(new).alias("blocks")))
        told = seen.get
        return frame, told["n"], bytes(told["blocks"])

    # expressions over the columns of the frames: the same in every level
    cell, value = F.col("cell"), F.col("value")
    owner, mine, key_of_own = layout.owner_of_value(cell, value).alias("owner"), cell == F.col("owner"), layout.key_at_owner(cell, value)
    sender, source = layout.sender(cell).alias("sender"), (F.lit(None).cast("long") if late else layout.source(cell, F.col("key"))).alias("u")
    found_new, fresh_new = F.when(mine, key_of_own), F.col("key")
    as_front = lambda frame, level: frame.select("cell", key_of_own.alias("key"), "value", "sender", "u", F.lit(level).alias("level"))

    with held(spark, PLACED):
        # from a column, not a constant: Spark would not know where a constant was dealt to
        start = spark.range(root, root + 1).select(*(x.alias(k) for k, x in layout.root(F.col("id")).items()), F.lit(None).cast("int").alias("sender"), F.col("id").alias("u"), F.lit(0).alias("level"))
        front, n, blocks = watched(start.repartition(layout.cells, "cell"), fresh_new)
        out.fronts.append(front)
        #: of the last levels: what the cells found, what of it they own, and what they received
        found_before: list[DataFrame] = []
        own_before: list[DataFrame] = []
        received_before: list[DataFrame] = [front]
        reached = Reached() if state == "bits" else None
        if reached:
            reached.add(front)
        level = 0
        while n and (max_level is None or level < max_level):
            level += 1
            clock = time.perf_counter()
            gathered = passed(level, "expand", expanded(front, graph, codec))
            adjacency = graph.touched(blocks)
            if kernel == "arrow":
                scanned = expand_cells(gathered, adjacency, group).repartition(layout.cells, "cell")
            else:
                scanned = gathered.join(adjacency.hint("merge"), ["cell", "key"]).select("cell", "key", F.explode("targets").alias("value"))
            known = [] if reached else [*(found_before[-2:] if dedup == "history" else own_before[-2:]), *received_before[-2:]]
            found = _without(scanned.select("cell", "value", "key"), *known) if dedup == "receiver" else _once(scanned, known, once)
            found = reached.without(found) if reached else found
            found, n, blocks = watched(found.select("cell", "value", "key", owner, F.lit(level).alias("level")), found_new)
            out.found.append(found)
            own = found.where(mine)
            own = own.groupBy("cell", "value").agg(F.min("key").alias("key")) if dedup == "receiver" else own
            own = own.select("cell", "value", sender, source)
            passed(level, "expansion")
            front, received = as_front(own, level), None
            if layout.folds:
                sent = passed(level, "fold", folded(found, graph, codec, late))
                known = [] if reached else [*own_before[-2:], *received_before[-2:]]
                if rule == "smallest":
                    front, n, blocks = watched(as_front(_smallest(own, sent, known), level), fresh_new)
                    own, received = front, None
                else:
                    fresh = _fresh(sent, [own, *known], late)
                    fresh = reached.without(fresh) if reached else fresh
                    received, more, more_blocks = watched(as_front(fresh, level), fresh_new)
                    front, n, blocks = front.unionAll(received), n + more, either(blocks, more_blocks)
            else:
                passed(level, "fold")
            passed(level, "update")
            if n:
                out.fronts.append(front)
                found_before.append(found)
                own_before.append(own)
                received_before += [] if received is None else [received]
                if reached:
                    reached.add(found, *([] if received is None else [received]))
                out._gather()
    return out
