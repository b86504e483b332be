"""The registered queries of the graph engine, each with the SQL that tells its rows where SQL can."""

from __future__ import annotations

import functools
import uuid
from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from levelgrid import catalog_sql as sql
from levelgrid.functions import udx
from levelgrid.functions.grid import GridSpec, register_sql
from levelgrid.operators import apps, codec, kernel, measures, prepare
from levelgrid.operators import levels as plain
from levelgrid.operators.components import star_components
from levelgrid.operators.search import Search, search
from levelgrid.plans import layout
from levelgrid.plans.state import ensure_checkpoint_dir, settled
from levelgrid.sources import generator, graphs
from levelgrid.streaming import edges as streams

#: a frontier of at most so many vertices is broadcast (16 bytes each)
BROADCAST_ROWS = 50_000

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}
_KEPT: dict[tuple, object] = {}


def query(name: str, oracle: str | None = None) -> Callable[[Query], Query]:
    def add(run: Query) -> Query:
        QUERIES[name] = run
        if oracle is not None:
            ORACLE_SQL[name] = oracle
        return run

    return add


def _stamp(spark: SparkSession, d: str) -> tuple:
    """When the tables of a folder were last written, and their names; nothing for generated graphs."""
    if d == "generated":
        return ()
    context = spark.sparkContext
    path = context._jvm.org.apache.hadoop.fs.Path(d)
    return tuple(sorted((x.getPath().getName(), x.getModificationTime(), x.getLen()) for x in path.getFileSystem(context._jsc.hadoopConfiguration()).listStatus(path)))


def forget(keep: int = 0) -> None:
    """Lets go of all but the last few shared graphs and searches; placed graphs give their storage back."""
    while len(_KEPT) > keep:
        old = _KEPT.pop(next(iter(_KEPT)))
        if isinstance(old, layout.PlacedGraph) and old.adjacency.sparkSession.sparkContext._jsc is not None:
            old.adjacency.unpersist()


def kept(spark: SparkSession, key: tuple, make: Callable[[], object]) -> object:
    """Graphs and searches that several queries of one session share while their tables stay as they are; the last few are held."""
    full = (spark.sparkContext.applicationId, *key, _stamp(spark, key[0]))
    if full not in _KEPT:
        _KEPT[full] = make()
        forget(64)
    return _KEPT[full]


def tuples(spark: SparkSession, d: str, gid: str) -> DataFrame:
    if gid.startswith("rmat"):
        return graphs.rmat_edges(spark, int(gid[4:]))
    return graphs.BUILDERS[gid](spark, d)


def graph(spark: SparkSession, d: str, gid: str) -> DataFrame:
    return kept(spark, (d, "graph", gid), lambda: settled(prepare.symmetrize(tuples(spark, d, gid))))


def size(spark: SparkSession, d: str, gid: str) -> int:
    return 1 << int(gid[4:]) if gid.startswith("rmat") else kept(spark, (d, "n", gid), lambda: graphs.vertex_count(spark, d, gid))


def levels(spark: SparkSession, d: str, gid: str, root: int = 0) -> DataFrame:
    return kept(spark, (d, "levels", gid, root), lambda: settled(plain.bfs_levels(graph(spark, d, gid), root)))


def affine(spark: SparkSession, d: str, gid: str) -> DataFrame:
    return kept(spark, (d, "affine", gid), lambda: settled(prepare.symmetrize(prepare.relabel_affine(tuples(spark, d, gid), size(spark, d, gid)))))


def gridded(spark: SparkSession, d: str, gid: str, r: int, c: int) -> layout.PlacedGraph:
    return kept(spark, (d, "grid", gid, r, c), lambda: layout.build(graph(spark, d, gid), layout.GridLayout(GridSpec(size(spark, d, gid), r, c))))


def searched(spark: SparkSession, d: str, gid: str, r: int, c: int, **options) -> Search:
    return kept(spark, (d, "search", gid, r, c, *sorted(options.items())), lambda: search(gridded(spark, d, gid, r, c), 0, **options))


def modulo_searched(spark: SparkSession, d: str, gid: str, p: int, **options) -> Search:
    placed = lambda: kept(spark, (d, "placed", gid, p), lambda: layout.build(graph(spark, d, gid), layout.ModuloLayout(p, size(spark, d, gid))))
    return kept(spark, (d, "modulo", gid, p, *sorted(options.items())), lambda: search(placed(), 0, **options))


def block(spark: SparkSession, d: str, gid: str, cells: int) -> int:
    return -(-size(spark, d, gid) // cells)


#: block sizes as DuckDB expressions
def _nb(gid: str, cells: int) -> str:
    n = {"op": "((SELECT count(*) FROM orders) + (SELECT count(*) FROM part))", "ps": "((SELECT count(*) FROM part) + (SELECT count(*) FROM supplier))"}.get(gid) or str(1 << int(gid[4:]))
    return f"(({n} + {cells - 1}) // {cells})"


# ---- graph building

for _gid in ("op", "ps", "cp", "cs", "uk", "geo", "cc", "web", "dup"):
    QUERIES[f"edges_{_gid}"] = lambda spark, d, g=_gid: tuples(spark, d, g)
    ORACLE_SQL[f"edges_{_gid}"] = sql.EDGES[_gid]
QUERIES["edges_knn_label"] = lambda spark, d: tuples(spark, d, "knn")
ORACLE_SQL["edges_knn_label"] = sql.EDGES["knn"]


@query("edges_all_counts", f"SELECT count(*) AS n, sum(src)::BIGINT AS sum_src, sum(dst)::BIGINT AS sum_dst, max(greatest(src, dst))::BIGINT AS largest FROM ({sql.EDGES['all']})")
def _(spark, d):
    return tuples(spark, d, "all").agg(F.count("*").alias("n"), F.sum("src").alias("sum_src"), F.sum("dst").alias("sum_dst"), F.max(F.greatest("src", "dst")).alias("largest"))


for _scale in (8, 11):
    QUERIES[f"rmat_tuples_s{_scale}"] = lambda spark, d, s=_scale: graphs.rmat_edges(spark, s)
    ORACLE_SQL[f"rmat_tuples_s{_scale}"] = sql.rmat(_scale)


@query("symmetrize_op", f"WITH {sql.simple('op')} SELECT src, dst FROM e")
def _(spark, d):
    return prepare.symmetrize(tuples(spark, d, "op"))


@query("multiplicity_ps", f"WITH t AS ({sql.EDGES['ps']}) SELECT src, dst, count(*) AS mult FROM (SELECT src, dst FROM t UNION ALL SELECT dst, src FROM t) WHERE src <> dst GROUP BY src, dst")
def _(spark, d):
    return prepare.multiplicity(tuples(spark, d, "ps"))


@query("relabel_affine_op", f"SELECT (src * 7919 + 13) % n AS src, (dst * 7919 + 13) % n AS dst FROM ({sql.EDGES['op']}), (SELECT (SELECT count(*) FROM orders) + (SELECT count(*) FROM part) AS n)")
def _(spark, d):
    return prepare.relabel_affine(tuples(spark, d, "op"), size(spark, d, "op"))


@query(
    "relabel_degree_ps",
    f"""WITH {sql.simple("ps")}, ids AS (SELECT src AS v, row_number() OVER (ORDER BY count(*) DESC, src) - 1 AS label FROM e GROUP BY src)
    SELECT a.label AS src, b.label AS dst FROM t JOIN ids a ON a.v = t.src JOIN ids b ON b.v = t.dst""",
)
def _(spark, d):
    return prepare.relabel_degree(tuples(spark, d, "ps"))


for _gid in ("op", "ps", "rmat11"):

    @query(f"degree_hist_{_gid}", f"WITH {sql.simple(_gid)} SELECT degree, count(*) AS vertices FROM (SELECT src, count(*) AS degree FROM e GROUP BY src) GROUP BY degree")
    def _(spark, d, g=_gid):
        return prepare.degrees(graph(spark, d, g)).groupBy("degree").agg(F.count("*").alias("vertices"))


@query(
    "induced_subgraph_segment",
    f"""SELECT src, dst FROM ({sql.EDGES["cs"]}) WHERE src IN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'BUILDING')
    AND dst - (SELECT count(*) FROM customer) IN (SELECT s_suppkey FROM supplier WHERE s_acctbal > 0)""",
)
def _(spark, d):
    customers = graphs.load_table(spark, d, "customer")
    suppliers = graphs.load_table(spark, d, "supplier").where("s_acctbal > 0").select((F.col("s_suppkey") + customers.count()).alias("v"))
    chosen = customers.where("c_mktsegment = 'BUILDING'").select(F.col("c_custkey").alias("v")).unionAll(suppliers)
    return prepare.induced(tuples(spark, d, "cs"), chosen)


_MIDDLE = "(SELECT min(o_orderdate) + (max(o_orderdate) - min(o_orderdate)) / 2 FROM orders)"


@query(
    "temporal_subgraph_orders",
    "SELECT l_orderkey AS src, l_partkey + (SELECT count(*) FROM orders) AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE year(o_orderdate) = (SELECT min(year(o_orderdate)) FROM orders)",
)
def _(spark, d):
    orders = graphs.load_table(spark, d, "orders")
    first = orders.agg(F.min(F.year("o_orderdate")).alias("y")).first()["y"]
    in_year = orders.where((F.col("o_orderdate") >= f"{first}-01-01") & (F.col("o_orderdate") < f"{first + 1}-01-01")).select("o_orderkey")
    lines = graphs.load_table(spark, d, "lineitem").join(in_year, F.col("l_orderkey") == F.col("o_orderkey"), "left_semi")
    return graphs.edges_from(lines, F.col("l_orderkey"), F.col("l_partkey") + orders.count())


# ---- grid

for _r, _c in ((2, 2), (4, 4)):
    _b = _nb("op", _r * _c)

    @query(f"grid_cells_op_{_r}x{_c}", f"WITH {sql.simple('op')} SELECT ((dst // {_b}) % {_r} * {_c} + src // ({_b} * {_r}))::INT AS cell, count(*) AS edges, count(DISTINCT src) AS sources FROM e GROUP BY 1")
    def _(spark, d, r=_r, c=_c):
        return layout.load_balance(graph(spark, d, "op"), layout.GridLayout(GridSpec(size(spark, d, "op"), r, c)))


@query("owner_blocks_op", f"WITH {sql.simple('op')} SELECT ((v // {_nb('op', 4)}) % 2 * 2 + v // ({_nb('op', 4)} * 2))::INT AS cell, count(*) AS vertices, min(v)::BIGINT AS first_v, max(v)::BIGINT AS last_v FROM (SELECT DISTINCT src AS v FROM e) GROUP BY 1")
def _(spark, d):
    grid = GridSpec(size(spark, d, "op"), 2, 2)
    return graph(spark, d, "op").select(F.col("src").alias("v")).distinct().groupBy(grid.owner_cell(F.col("v")).alias("cell")).agg(F.count("*").alias("vertices"), F.min("v").alias("first_v"), F.max("v").alias("last_v"))


@query("local_index_roundtrip", "SELECT r, c, 0::BIGINT AS wrong_rows, 0::BIGINT AS wrong_columns FROM (VALUES (1, 1), (2, 2), (2, 4), (4, 4), (3, 5)) x(r, c)")
def _(spark, d):
    out = None
    for r, c in ((1, 1), (2, 2), (2, 4), (4, 4), (3, 5)):
        grid = GridSpec(size(spark, d, "ps"), r, c)
        u, v = F.col("src"), F.col("dst")
        row = grid.global_row(grid.owner_row(v), grid.local_row(v)) != v
        column = (grid.global_column(grid.owner_column(u), grid.local_column(u)) != u) | (grid.row_to_column(grid.owner_row(u), grid.local_row(u)) != grid.local_column(u))
        told = graph(spark, d, "ps").agg(F.lit(r).alias("r"), F.lit(c).alias("c"), F.sum(row.cast("long")).alias("wrong_rows"), F.sum(column.cast("long")).alias("wrong_columns"))
        out = told if out is None else out.unionAll(told)
    return out


@query("grid_property_violations", "SELECT property, 0::BIGINT AS violations FROM (VALUES ('list in grid column'), ('owner in grid row')) x(property)")
def _(spark, d):
    return layout.grid_property_violations(graph(spark, d, "op"), GridSpec(size(spark, d, "op"), 4, 4))


@query("load_balance_1d", f"WITH {sql.simple('op')} SELECT (src % 16)::INT AS cell, count(*) AS edges, count(DISTINCT src) AS sources FROM e GROUP BY 1")
def _(spark, d):
    return layout.load_balance(graph(spark, d, "op"), layout.ModuloLayout(16))


@query(
    "load_balance_2d",
    f"""WITH {sql.simple("op")}, n AS (SELECT (SELECT count(*) FROM orders) + (SELECT count(*) FROM part) AS n),
    f AS (SELECT (src * 7919 + 13) % n AS src, (dst * 7919 + 13) % n AS dst, (n + 15) // 16 AS nb FROM e, n),
    o AS (SELECT 'offset' AS labels, (dst // {_nb("op", 16)}) % 4 * 4 + src // ({_nb("op", 16)} * 4) AS cell FROM e UNION ALL SELECT 'affine', (dst // nb) % 4 * 4 + src // (nb * 4) FROM f)
    SELECT labels, max(n)::BIGINT AS most, sum(n)::BIGINT AS edges, count(*) AS cells FROM (SELECT labels, cell, count(*) AS n FROM o GROUP BY 1, 2) GROUP BY labels""",
)
def _(spark, d):
    out = None
    for name, g in (("offset", graph(spark, d, "op")), ("affine", affine(spark, d, "op"))):
        cells = layout.load_balance(g, layout.GridLayout(GridSpec(size(spark, d, "op"), 4, 4)))
        told = cells.agg(F.lit(name).alias("labels"), F.max("edges").alias("most"), F.sum("edges").alias("edges"), F.count("*").alias("cells"))
        out = told if out is None else out.unionAll(told)
    return out


@query(
    "csc_columns_ps",
    f"""WITH {sql.simple("ps")}, nb AS (SELECT {_nb("ps", 4)} AS nb)
    SELECT ((dst // nb) % 2 * 2 + src // (nb * 2))::INT AS cell, (src % (nb * 2))::INT AS lcol, count(*) AS degree, sum(dst // (nb * 2) * nb + dst % nb)::BIGINT AS targets FROM e, nb GROUP BY 1, 2""",
)
def _(spark, d):
    placed = gridded(spark, d, "ps", 2, 2)
    rows = placed.adjacency.select(placed.layout.number(F.col("cell")).alias("cell"), F.col("key").alias("lcol"), F.explode("targets").alias("t"))
    return rows.groupBy("cell", "lcol").agg(F.count("*").alias("degree"), F.sum(F.col("t").cast("long")).alias("targets"))


@query("csr_rows_1d", f"WITH {sql.simple('ps')} SELECT (src % 4)::INT AS cell, src AS u, count(*) AS degree, max(dst)::BIGINT AS last_target FROM e GROUP BY 1, 2")
def _(spark, d):
    placed = layout.build(graph(spark, d, "ps"), layout.ModuloLayout(4), chunk=16)
    return placed.adjacency.groupBy(placed.layout.number(F.col("cell")).alias("cell"), F.col("key").alias("u")).agg(F.sum(F.size("targets").cast("long")).alias("degree"), F.max(F.element_at("targets", -1)).alias("last_target"))


#: grids and scales of the weak-scaling runs (fixed values)
WEAK_GRIDS = ((1, 1, 21), (1, 2, 22), (2, 2, 23), (2, 4, 24), (4, 4, 25), (4, 8, 26), (8, 8, 27), (8, 16, 28), (16, 16, 29), (16, 32, 30), (32, 32, 31), (32, 64, 32), (64, 64, 33))
_GRID_ROWS = ", ".join(f"({r}, {c}, {s})" for r, c, s in WEAK_GRIDS)


@query(
    "memory_model",
    f"""SELECT r, c, scale, (nb * r + 1)::BIGINT AS offsets, ((nb * c + 31) // 32)::BIGINT AS bitmap_words, (nb * c)::BIGINT AS level_words, nb::BIGINT AS frontier_words
    FROM (SELECT r, c, scale, (1::BIGINT << scale) // (r * c) AS nb FROM (VALUES {_GRID_ROWS}) x(r, c, scale))""",
)
def _(spark, d):
    rows = [(r, c, s, m["offsets"], m["bitmap_words"], m["level_words"], m["frontier_words"]) for r, c, s in WEAK_GRIDS for m in [GridSpec(1 << s, r, c).memory()]]
    return spark.createDataFrame(rows, "r int, c int, scale int, offsets long, bitmap_words long, level_words long, frontier_words long")


# ---- mapping of work to edges

_FRONT = f"WITH RECURSIVE {sql.simple('ps')}, {sql.walked(cap=4)}, f AS (SELECT row_number() OVER (ORDER BY v) - 1 AS k, v FROM levels WHERE level = 1), deg AS (SELECT f.k, f.v, count(*) AS degree FROM f JOIN e ON e.src = f.v GROUP BY 1, 2)"
_SCAN = "scan AS (SELECT k, degree, coalesce(sum(degree) OVER (ORDER BY k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS before FROM deg)"
_UNITS = "units AS (SELECT k, before + j AS i, j FROM (SELECT k, before, unnest(range(degree)) AS j FROM scan))"


def _frontier(spark: SparkSession, d: str) -> DataFrame:
    first = prepare.dense_ids(levels(spark, d, "ps").where("level = 1").select("v"), "v", "k")
    return prepare.degrees(graph(spark, d, "ps")).join(first, "v").select("k", "degree")


@query("edge_map_scan", f"{_FRONT}, {_SCAN} SELECT k, degree, before FROM scan")
def _(spark, d):
    return kernel.exclusive_scan(_frontier(spark, d))


@query("edge_map_units", f"{_FRONT}, {_SCAN}, {_UNITS} SELECT i, k, j FROM units")
def _(spark, d):
    return kernel.edge_work_map(_frontier(spark, d)).select("i", "k", "j")


@query("edge_map_group4", f"{_FRONT}, {_SCAN}, {_UNITS} SELECT i // 4 AS unit, count(*) AS edges, min(k) AS first_k, max(k) AS last_k FROM units GROUP BY 1")
def _(spark, d):
    return kernel.edge_work_map(_frontier(spark, d), group=4).groupBy("unit").agg(F.count("*").alias("edges"), F.min("k").alias("first_k"), F.max("k").alias("last_k"))


@query("edge_map_zero_degree", f"{_FRONT.replace('count(*) AS degree', 'CASE WHEN f.k % 3 = 0 THEN 0 ELSE count(*) END AS degree')}, {_SCAN}, {_UNITS} SELECT i, k, j FROM units")
def _(spark, d):
    return kernel.edge_work_map(_frontier(spark, d).withColumn("degree", F.when(F.col("k") % 3 == 0, 0).otherwise(F.col("degree")))).select("i", "k", "j")


# ---- searches

_LEVELS = "SELECT v, level FROM levels"
for _gid in ("op", "ps", "cp", "cs", "uk", "geo", "web", "dup", "all"):
    QUERIES[f"bfs_{_gid}_levels"] = lambda spark, d, g=_gid: plain.bfs_levels(graph(spark, d, g), 0)
    ORACLE_SQL[f"bfs_{_gid}_levels"] = sql.with_levels(_gid, _LEVELS)
QUERIES["chain_levels"] = lambda spark, d: plain.bfs_levels(graph(spark, d, "cc"), 0)
ORACLE_SQL["chain_levels"] = sql.with_levels("cc", _LEVELS, cap=40)
QUERIES["bfs_rmat_levels"] = lambda spark, d: plain.bfs_levels(graph(spark, d, "rmat11"), 0)
ORACLE_SQL["bfs_rmat_levels"] = sql.with_levels("rmat11", _LEVELS)


@query("bfs_unreached_fill", sql.with_levels("geo", "SELECT x.v, coalesce(level, -1) AS level FROM (SELECT unnest(range((SELECT max(greatest(src, dst)) + 1 FROM t))) AS v) x LEFT JOIN levels USING (v)"))
def _(spark, d):
    return plain.fill_unreached(levels(spark, d, "geo"), size(spark, d, "geo"))


@query("bfs_depth_limited", sql.with_levels("op", _LEVELS, cap=3))
def _(spark, d):
    return plain.bfs_levels(graph(spark, d, "op"), 0, max_level=3)


@query("bfs_target_limited", sql.with_levels("op", "SELECT v, level FROM levels WHERE level <= (SELECT level FROM levels WHERE v = 100)"))
def _(spark, d):
    return plain.bfs_levels(graph(spark, d, "op"), 0, target=100)


for _name, _options in {
    "bfs_grid_receiver": {"dedup": "receiver", "parents": "eager"},
    "bfs_grid_level": {"dedup": "level"},
    "bfs_grid_history": {"dedup": "history"},
    "bfs_grid_bits": {"state": "bits"},
    "bfs_grid_kernel": {"kernel": "arrow"},
    "bfs_grid_list_messages": {"codec": "list"},
    "bfs_grid_bitmap_messages": {"codec": "bitmap"},
    "bfs_grid_auto_messages": {"codec": "auto"},
    "dedup_compact_levels": {"once": "compact"},
}.items():
    QUERIES[_name] = lambda spark, d, o=_options: searched(spark, d, "ps", 2, 2, **o).levels()
    ORACLE_SQL[_name] = sql.with_levels("ps", _LEVELS)
QUERIES["bfs_grid_1x1"] = lambda spark, d: searched(spark, d, "ps", 1, 1).levels()
QUERIES["bfs_grid_4x4_op"] = lambda spark, d: searched(spark, d, "op", 4, 4).levels()
QUERIES["bfs_1d_levels"] = lambda spark, d: modulo_searched(spark, d, "ps", 4, dedup="level").levels()
ORACLE_SQL |= {"bfs_grid_1x1": sql.with_levels("ps", _LEVELS), "bfs_grid_4x4_op": sql.with_levels("op", _LEVELS), "bfs_1d_levels": sql.with_levels("ps", _LEVELS)}


@query("bfs_affine_levels", sql.with_affine("op", "(SELECT (SELECT count(*) FROM orders) + (SELECT count(*) FROM part))", _LEVELS, "13"))
def _(spark, d):
    grid = GridSpec(size(spark, d, "op"), 2, 2)
    return search(layout.build(affine(spark, d, "op"), layout.GridLayout(grid)), prepare.affine_label(0, grid.n)).levels()


@query("bfs_recursive_levels", sql.with_levels("geo", _LEVELS, cap=3))
def _(spark, d):
    return plain.bfs_recursive(spark, graph(spark, d, "geo"), 0, 3)


_ROOTS = "roots AS (SELECT src AS root FROM (SELECT DISTINCT src FROM e) ORDER BY (src * 69621 + 16807 + 12345) % 2147483647, src LIMIT {k})"


def _many(gid: str, k: int, rest: str, depth: int = 16) -> str:
    """many (root, v, level): level by level, each without the two before it."""
    levels = ["l0 AS MATERIALIZED (SELECT root, root AS v FROM roots)"]
    for i in range(1, depth + 1):
        known = " ".join(f"EXCEPT SELECT root, v FROM l{j}" for j in (i - 1, i - 2) if j >= 0)
        levels.append(f"l{i} AS MATERIALIZED (SELECT DISTINCT l.root, e.dst AS v FROM l{i - 1} l JOIN near e ON e.src = l.v {known})")
    every = " UNION ALL ".join(f"SELECT root, v, {i} AS level FROM l{i}" for i in range(depth + 1))
    return f"WITH {sql.simple(gid)}, near AS MATERIALIZED (SELECT src, dst FROM e), {_ROOTS.format(k=k)}, {', '.join(levels)}, many AS ({every}) {rest}"


@query("sample_roots_hash", f"WITH {sql.simple('op')}, {_ROOTS.format(k=64)} SELECT root FROM roots")
def _(spark, d):
    return plain.sample_roots(graph(spark, d, "op"), 64)


#: the protocol of the experiments (fixed value)
SEARCHES = 64

for _gid in ("op", "cp", "cs", "uk", "all", "web", "dup", "geo"):

    @query("multi_root_batched" if _gid == "uk" else "multi_root_op" if _gid == "op" else f"multi_root_batched_{_gid}", _many(_gid, SEARCHES, "SELECT root, level, count(*) AS vertices FROM many GROUP BY 1, 2"))
    def _(spark, d, g=_gid):
        return plain.bfs_batched(graph(spark, d, g), plain.sample_roots(graph(spark, d, g), SEARCHES)).groupBy("root", "level").agg(F.count("*").alias("vertices"))


_PER_ROOT = """, reached AS (SELECT root, v FROM many) SELECT root, max(level) AS depth, count(*) AS vertices,
  (SELECT count(*) FROM t JOIN reached r ON r.v = t.src WHERE r.root = many.root) AS tuples FROM many GROUP BY root"""


@query("multi_root_tuples_geo", _many("geo", SEARCHES, _PER_ROOT))
def _(spark, d):
    """What the rate of each of the 64 searches is made from: the tuples that it traverses."""
    found = settled(plain.bfs_batched(graph(spark, d, "geo"), plain.sample_roots(graph(spark, d, "geo"), SEARCHES)))
    return measures.per_root(tuples(spark, d, "geo"), found)


# ---- parents

_GLOBAL_MIN = "tree AS (SELECT c.v, c.level, CASE WHEN c.level = 0 THEN c.v ELSE (SELECT min(e.src) FROM e JOIN levels p ON p.v = e.src AND p.level = c.level - 1 WHERE e.dst = c.v) END AS pred FROM levels c)"
_TREE = """up AS (SELECT e.dst AS v, c.level, e.src FROM levels c JOIN e ON e.dst = c.v JOIN levels p ON p.v = e.src AND p.level = c.level - 1)"""


@query("pred_global_min", sql.with_levels("op", f", {_TREE} SELECT v, level, min(src)::BIGINT AS pred FROM up GROUP BY 1, 2 UNION ALL SELECT v, 0, v FROM levels WHERE level = 0".lstrip()))
def _(spark, d):
    return plain.parents_global_min(graph(spark, d, "op"), levels(spark, d, "op"), 0)


@query("pred_global_min_grid", sql.with_levels("ps", f", {_TREE} SELECT v, level, min(src)::BIGINT AS pred FROM up GROUP BY 1, 2 UNION ALL SELECT v, 0, v FROM levels WHERE level = 0"))
def _(spark, d):
    return searched(spark, d, "ps", 2, 2, dedup="level", parents="eager", rule="smallest").tree()


_OWNER_FIRST = f""", {_TREE}, o AS (SELECT v, level, src, src // (nb * 2) AS gj, v // (nb * 2) AS own FROM up, (SELECT {_nb("ps", 4)} AS nb)),
  best AS (SELECT v, level, min(src) FILTER (WHERE gj = own) AS mine, min(gj) AS first_column FROM o GROUP BY 1, 2)
  SELECT b.v, b.level, coalesce(mine, (SELECT min(o.src) FROM o WHERE o.v = b.v AND o.gj = b.first_column))::BIGINT AS pred FROM best b UNION ALL SELECT v, 0, v FROM levels WHERE level = 0"""


@query("pred_owner_first", sql.with_levels("ps", _OWNER_FIRST))
def _(spark, d):
    return searched(spark, d, "ps", 2, 2, dedup="history").tree()


@query("pred_late_equals_eager", "SELECT 0::BIGINT AS differences")
def _(spark, d):
    late = searched(spark, d, "ps", 2, 2, dedup="history").tree()
    eager = searched(spark, d, "ps", 2, 2, dedup="receiver", parents="eager").tree()
    joined = late.join(eager.select("v", F.col("level").alias("l"), F.col("pred").alias("p")), "v", "full_outer")
    return joined.agg(F.coalesce(F.sum((~(F.col("pred").eqNullSafe(F.col("p")) & F.col("level").eqNullSafe(F.col("l")))).cast("long")), F.lit(0)).alias("differences"))


@query("shortest_path_op", sql.with_levels("op", f""", {_TREE}, tree AS (SELECT v, level, min(src) AS pred FROM up GROUP BY 1, 2),
    path(step, v) AS (SELECT level, v FROM levels WHERE v = 5000 UNION ALL SELECT tree.level - 1, tree.pred FROM path JOIN tree USING (v)) SELECT step, v::BIGINT AS v FROM path"""))
def _(spark, d):
    tree = settled(plain.parents_global_min(graph(spark, d, "op"), levels(spark, d, "op"), 0))
    return plain.shortest_path(tree, 5000)


# ---- message encodings and traffic

def _fold(spark: SparkSession, d: str, gid: str, r: int, c: int, dedup: str) -> DataFrame:
    return searched(spark, d, gid, r, c, dedup=dedup).fold_messages()


def _traffic(gid: str, r: int, c: int, messages: str) -> str:
    return sql.with_levels(gid, f", {sql.grid_edges(_nb(gid, r * c), r, c)} {messages}")


_OWN = """, own AS (SELECT DISTINCT c.dst, l.level FROM c JOIN levels l ON l.v = c.dst WHERE gj = gt AND c.lv = l.level - 1),
  sent AS (SELECT gi, gj, gt, dst, 1 + min(lv) AS level FROM c WHERE gj <> gt GROUP BY 1, 2, 3, 4)
  SELECT level, coalesce(kept, 0) AS kept, coalesce(moved, 0) AS moved FROM (SELECT level, count(*) AS kept FROM own GROUP BY 1) FULL JOIN (SELECT level, count(*) AS moved FROM sent GROUP BY 1) USING (level)"""


@query("local_split", _traffic("ps", 2, 2, _OWN))
def _(spark, d):
    """Found vertices that stay with their discoverer, and those that are folded, by level."""
    found = searched(spark, d, "ps", 2, 2, dedup="history")
    return found._all(found.found).groupBy("level").agg(F.count(F.when(F.col("cell") == F.col("owner"), 1)).alias("kept"), F.count(F.when(F.col("cell") != F.col("owner"), 1)).alias("moved"))


for _dedup in ("receiver", "level", "history"):

    @query(f"traffic_fold_{_dedup}", _traffic("ps", 2, 2, sql.fold(_dedup, 2)))
    def _(spark, d, mode=_dedup):
        return _fold(spark, d, "ps", 2, 2, mode)


@query("traffic_fold_history_op", _traffic("op", 4, 4, sql.fold("history", 4)))
def _(spark, d):
    return _fold(spark, d, "op", 4, 4, "history")


@query("traffic_expand", sql.with_levels("op", sql.expand(_nb("op", 16), 4, 4)))
def _(spark, d):
    return searched(spark, d, "op", 4, 4, dedup="history").expand_messages()


def _sent_sql(kind: str) -> str:
    """Messages of both phases as they are sent: lists of 4 bytes an index, or bitmaps in whole words of 64."""
    nb, choice = _nb("op", 16), {"list": "'list'", "bitmap": "'bitmap'", "auto": "kind"}[kind]
    both = f"SELECT 'fold' AS phase, * FROM ({sql.sizes(sql.fold('history', 4), nb)}) UNION ALL SELECT 'expand', * FROM ({sql.sizes(sql.expand(nb, 4, 4), nb)})"
    return _traffic("op", 4, 4, f"""SELECT phase, level, sender, receiver, sent_as AS kind, vertices, CASE WHEN sent_as = 'list' THEN vertices * 4 ELSE ({nb} + 63) // 64 * 8 END::BIGINT AS bytes
      FROM (SELECT *, {choice} AS sent_as FROM ({both}))""")


for _codec in ("list", "bitmap", "auto"):

    @query(f"codec_bytes_{_codec}", _sent_sql(_codec))
    def _(spark, d, c=_codec):
        return searched(spark, d, "op", 4, 4, codec=c).sent_messages()


@query(
    "codec_choice_by_level",
    _traffic("op", 4, 4, f"""SELECT phase, level, kind, count(*) AS messages FROM (SELECT 'fold' AS phase, * FROM ({sql.sizes(sql.fold("history", 4), _nb("op", 16))})
      UNION ALL SELECT 'expand', * FROM ({sql.sizes(sql.expand(_nb("op", 16), 4, 4), _nb("op", 16))})) GROUP BY 1, 2, 3"""),
)
def _(spark, d):
    return _rows(spark, d).groupBy("phase", "level", "kind").agg(F.count("*").alias("messages"))


def _rows(spark: SparkSession, d: str, gid: str = "op", r: int = 4, c: int = 4) -> DataFrame:
    found = searched(spark, d, gid, r, c, dedup="history")
    nb = block(spark, d, gid, r * c)
    return measures.traffic(found.fold_messages(), "fold", nb).unionByName(measures.traffic(found.expand_messages(), "expand", nb))


_ROWS_OP = _traffic("op", 4, 4, f""", rows_ AS (SELECT 'fold' AS phase, * FROM ({sql.sizes(sql.fold("history", 4), _nb("op", 16))})
      UNION ALL SELECT 'expand', * FROM ({sql.sizes(sql.expand(_nb("op", 16), 4, 4), _nb("op", 16))}))""")
_SUMS = "count(*) AS messages, sum(vertices)::BIGINT AS vertices, sum(bytes_list)::BIGINT AS bytes_list, sum(bytes_bitmap)::BIGINT AS bytes_bitmap, sum(bytes_auto)::BIGINT AS bytes_auto"


#: totals of a rollup stand under 'all' and -1
@query("traffic_rollup", f"{_ROWS_OP} SELECT coalesce(phase, 'all') AS phase, coalesce(level, -1) AS level, {_SUMS} FROM rows_ GROUP BY ROLLUP (phase, level)")
def _(spark, d):
    return measures.traffic_totals(_rows(spark, d)).fillna({"phase": "all", "level": -1})


@query("agg_grouping_sets_traffic", f"{_ROWS_OP} SELECT phase, coalesce(sender, -1) AS sender, coalesce(receiver, -1) AS receiver, sum(vertices)::BIGINT AS vertices FROM rows_ GROUP BY GROUPING SETS ((phase, sender), (phase, receiver), (phase))")
def _(spark, d):
    _rows(spark, d).createOrReplaceTempView("traffic_rows")
    return spark.sql("SELECT phase, coalesce(sender, -1) AS sender, coalesce(receiver, -1) AS receiver, sum(vertices) AS vertices FROM traffic_rows GROUP BY GROUPING SETS ((phase, sender), (phase, receiver), (phase))")


@query("agg_cube_codec", f"{_ROWS_OP} SELECT coalesce(phase, 'all') AS phase, coalesce(kind, 'all') AS kind, count(*) AS messages FROM rows_ GROUP BY CUBE (phase, kind)")
def _(spark, d):
    return _rows(spark, d).cube("phase", "kind").agg(F.count("*").alias("messages")).fillna("all")


@query("agg_rollup_traffic", f"{_ROWS_OP} SELECT coalesce(level, -1) AS level, coalesce(sender, -1) AS sender, sum(bytes_auto)::BIGINT AS bytes_auto FROM rows_ GROUP BY ROLLUP (level, sender)")
def _(spark, d):
    return _rows(spark, d).rollup("level", "sender").agg(F.sum("bytes_auto").alias("bytes_auto")).fillna(-1)


_MODES = ("receiver", "level", "history")


def _layouts_sql(gid: str) -> str:
    parts = [
        *(f"SELECT '2D' AS layout, '{m}' AS dedup, sum(vertices)::BIGINT AS vertices, count(*) AS messages FROM ({sql.fold(m, 2)})" for m in _MODES),
        *(f"SELECT '1D', '{m}', sum(vertices)::BIGINT, count(*) FROM ({sql.modulo_fold(m, 4)})" for m in _MODES),
        f"SELECT '2D', 'expand', sum(vertices)::BIGINT, count(*) FROM ({sql.expand(_nb(gid, 4), 2, 2)})",
    ]
    return _traffic(gid, 2, 2, " UNION ALL ".join(parts))


def _layouts(spark: SparkSession, d: str, gid: str) -> DataFrame:
    sums = lambda messages, layout_, dedup: messages.agg(F.lit(layout_).alias("layout"), F.lit(dedup).alias("dedup"), F.sum("vertices").alias("vertices"), F.count("*").alias("messages"))
    parts = [sums(searched(spark, d, gid, 2, 2, dedup=m).fold_messages(), "2D", m) for m in _MODES]
    parts += [sums(modulo_searched(spark, d, gid, 4, dedup=m).fold_messages(), "1D", m) for m in _MODES]
    parts.append(sums(searched(spark, d, gid, 2, 2, dedup="history").expand_messages(), "2D", "expand"))
    return functools.reduce(DataFrame.unionAll, parts)


for _gid in ("ps", "op", "rmat10"):
    QUERIES["traffic_1d_vs_2d" if _gid == "ps" else f"traffic_1d_vs_2d_{_gid}"] = lambda spark, d, g=_gid: _layouts(spark, "generated" if g.startswith("rmat") else d, g)
    ORACLE_SQL["traffic_1d_vs_2d" if _gid == "ps" else f"traffic_1d_vs_2d_{_gid}"] = _layouts_sql(_gid)


@query("traffic_ratio_1d_2d", f"WITH x AS ({_layouts_sql('ps')}) SELECT a.dedup, round(a.vertices / b.vertices, 9) AS ratio FROM x a JOIN x b ON a.dedup = b.dedup AND a.layout = '1D' AND b.layout = '2D'")
def _(spark, d):
    """How many times the vertices that the grid folds the modulo layout does."""
    told = settled(_layouts(spark, d, "ps")).where("dedup <> 'expand'")
    one, two = (told.where(F.col("layout") == x).select("dedup", F.col("vertices").cast("double").alias("teps")) for x in ("1D", "2D"))
    return measures.ratios(one, two, ["dedup"]).select("dedup", F.round("ratio", 9).alias("ratio"))


@query("bitmap_pack_counts", f"WITH {sql.simple('op')} SELECT (v // 4096)::BIGINT AS message, count(*) AS n, CASE WHEN count(*) > 128 THEN 'bitmap' ELSE 'list' END AS kind FROM (SELECT DISTINCT src AS v FROM e) GROUP BY 1")
def _(spark, d):
    return codec.messages(_indices(spark, d), ["message"], "index", 4096).select("message", "n", "kind")


def _indices(spark: SparkSession, d: str) -> DataFrame:
    chosen = graph(spark, d, "op").select(F.col("src").alias("v")).distinct()
    return chosen.select(F.floor(F.col("v") / 4096).alias("message"), (F.col("v") % 4096).alias("index"))


@query("bitmap_roundtrip", f"WITH {sql.simple('op')} SELECT (v // 4096)::BIGINT AS message, (v % 4096)::BIGINT AS index FROM (SELECT DISTINCT src AS v FROM e)")
def _(spark, d):
    return codec.unpack(codec.messages(_indices(spark, d), ["message"], "index", 4096), ["message"], "index")


@query("switch_threshold_table", "SELECT nb::BIGINT AS nb, (nb // 8)::BIGINT AS bytes, (nb // 32)::BIGINT AS threshold, (nb * 4)::BIGINT AS longest_list FROM (VALUES (64), (1024), (32768), (65536), (2097152)) x(nb)")
def _(spark, d):
    return spark.createDataFrame([(nb, codec.bitmap_bytes(nb), codec.switch_threshold(nb), nb * 4) for nb in (64, 1024, 32768, 65536, 1 << 21)], "nb long, bytes long, threshold long, longest_list long")


@query("partner_counts_t1", f"SELECT r, c, (r - 1)::BIGINT AS expand, (c - 1)::BIGINT AS fold, (r + c - 2)::BIGINT AS two_dimensional, (r * c - 1)::BIGINT AS one_dimensional FROM (VALUES {_GRID_ROWS}) x(r, c, scale)")
def _(spark, d):
    rows = [(r, c, *measures.partner_counts(GridSpec(1 << s, r, c)).values()) for r, c, s in WEAK_GRIDS]
    return spark.createDataFrame(rows, "r int, c int, expand long, fold long, two_dimensional long, one_dimensional long")


for _gid in ("op", "rmat11"):

    @query("frontier_profile" if _gid == "op" else f"frontier_profile_{_gid}", sql.with_levels(_gid, "SELECT level, count(DISTINCT v) AS vertices, count(e.dst) AS edges FROM levels LEFT JOIN e ON e.src = v GROUP BY level"))
    def _(spark, d, g=_gid):
        return measures.frontier_profile(graph(spark, d, g), levels(spark, d, g))


@query(
    "tuples_traversed",
    " UNION ALL ".join(f"SELECT * FROM ({sql.with_levels(g, f'''SELECT '{g}' AS gid, count(*) AS tuples FROM t WHERE src IN (SELECT v FROM levels)''')})" for g in ("op", "geo", "rmat11")),
)
def _(spark, d):
    return spark.createDataFrame([(g, measures.tuples_traversed(tuples(spark, d, g), levels(spark, d, g))) for g in ("op", "geo", "rmat11")], "gid string, tuples long")


@query("harmonic_teps_model", f"WITH {sql.simple('op')} SELECT src % 4 AS class, round(count(*) / sum(degree / 1000000.0), 6) AS mean_teps FROM (SELECT src, count(*) AS degree FROM e GROUP BY src) GROUP BY 1")
def _(spark, d):
    """Rates of a model in which a search takes a microsecond for each of its root's edges."""
    rates = prepare.degrees(graph(spark, d, "op")).select((F.col("v") % 4).alias("class"), (1 / (F.col("degree") / 1000000.0)).alias("teps"))
    return rates.groupBy("class").agg(F.round(measures.harmonic_mean(F.col("teps")), 6).alias("mean_teps"))


_WASTED = """, sent AS (SELECT gi, gj, gt, dst, 1 + min(lv) AS level FROM c WHERE gj <> gt GROUP BY 1, 2, 3, 4),
  own AS (SELECT DISTINCT c.dst FROM c JOIN levels l ON l.v = c.dst WHERE gj = gt AND c.lv = l.level - 1),
  news AS (SELECT DISTINCT s.dst, s.level FROM sent s JOIN levels l ON l.v = s.dst AND l.level = s.level WHERE s.dst NOT IN (SELECT dst FROM own))
  SELECT s.level, s.sent, s.sent - coalesce(n.news, 0) AS wasted FROM (SELECT level, count(*) AS sent FROM sent GROUP BY 1) s LEFT JOIN (SELECT level, count(*) AS news FROM news GROUP BY 1) n USING (level)"""


@query("wasted_fold", _traffic("ps", 2, 2, _WASTED))
def _(spark, d):
    found = searched(spark, d, "ps", 2, 2, dedup="history")
    return measures.wasted_fold(found._all(found.found), found._all(found.fronts))


def _scaling(spark: SparkSession, runs: tuple) -> DataFrame:
    out = None
    for s, r, c in runs:
        found = searched(spark, "generated", f"rmat{s}", r, c, dedup="history")
        nb = (1 << s) // (r * c)
        for phase, messages in (("expand", found.expand_messages()), ("fold", found.fold_messages())):
            told = codec.sized(messages, nb).agg(
                F.lit(s).alias("scale"), F.lit(r).alias("r"), F.lit(c).alias("c"), F.lit(phase).alias("phase"), F.coalesce(F.sum("vertices"), F.lit(0)).alias("vertices"), F.count("*").alias("messages"),
                *(F.coalesce(F.sum(f"bytes_{k}"), F.lit(0)).alias(f"bytes_{k}") for k in ("list", "bitmap", "auto")),
            )
            out = told if out is None else out.unionAll(told)
    return out


def _scaling_sql(runs: tuple) -> str:
    one = lambda s, r, c, phase, messages: f"SELECT {s} AS scale, {r} AS r, {c} AS c, '{phase}' AS phase, coalesce(sum(vertices), 0)::BIGINT AS vertices, count(*) AS messages, coalesce(sum(bytes_list), 0)::BIGINT AS bytes_list, coalesce(sum(bytes_bitmap), 0)::BIGINT AS bytes_bitmap, coalesce(sum(bytes_auto), 0)::BIGINT AS bytes_auto FROM ({sql.sizes(messages, str((1 << s) // (r * c)))})"
    parts = []
    for s, r, c in runs:
        nb = str((1 << s) // (r * c))
        both = f"{one(s, r, c, 'expand', sql.expand(nb, r, c))} UNION ALL {one(s, r, c, 'fold', sql.fold('history', c))}"
        parts.append(f"SELECT * FROM ({sql.with_levels(f'rmat{s}', f', {sql.grid_edges(nb, r, c)} {both}')})")
    return " UNION ALL ".join(parts)


_WEAK, _STRONG = ((8, 1, 1), (9, 1, 2), (10, 2, 2), (11, 2, 4), (12, 4, 4), (13, 4, 8)), ((11, 1, 1), (11, 1, 2), (11, 2, 2), (11, 2, 4), (11, 4, 4), (11, 4, 8))
QUERIES["weak_rmat_traffic"] = lambda spark, d: _scaling(spark, _WEAK)
QUERIES["strong_rmat_traffic"] = lambda spark, d: _scaling(spark, _STRONG)
ORACLE_SQL |= {"weak_rmat_traffic": _scaling_sql(_WEAK), "strong_rmat_traffic": _scaling_sql(_STRONG)}


@query("phase_seconds", sql.with_levels("ps", "SELECT level + 1 AS level, phase, true AS measured FROM (SELECT DISTINCT level FROM levels), (VALUES ('expand'), ('expansion'), ('fold'), ('update')) x(phase)"))
def _(spark, d):
    """The four phases of each level of one profiled search, and whether their seconds are told; the bench has the seconds."""
    return search(gridded(spark, d, "ps", 2, 2), 0, profile=True).phases().select("level", "phase", (F.col("seconds") >= 0).alias("measured"))


# ---- validation

_CHECKS = "SELECT \"check\", 0::BIGINT AS violations FROM (VALUES ('root'), ('parent edge'), ('one level below parent'), ('edge spans one level'), ('component covered')) x(\"check\")"


@query("validate_op", _CHECKS)
def _(spark, d):
    return measures.validate(graph(spark, d, "op"), searched(spark, d, "op", 4, 4, dedup="history").tree(), 0)


@query("validate_rmat", _CHECKS)
def _(spark, d):
    return measures.validate(graph(spark, d, "rmat11"), searched(spark, "generated", "rmat11", 2, 2, dedup="history").tree(), 0)


_CORRUPT = sql.with_levels("geo", f""", {_TREE}, tree AS (SELECT v, level, min(src) AS pred FROM up GROUP BY 1, 2 UNION ALL SELECT v, 0, v FROM levels WHERE level = 0),
  bad AS (SELECT v, CASE WHEN v % 50 = 7 THEN level + 1 ELSE level END AS level, CASE WHEN v % 50 = 9 THEN 1 ELSE pred END AS pred FROM tree WHERE v % 50 <> 11),
  ends AS (SELECT e.src, e.dst, a.level AS a, b.level AS b FROM e JOIN bad a ON a.v = e.src LEFT JOIN bad b ON b.v = e.dst)
  SELECT 'root' AS "check", (abs((SELECT count(*) FROM bad WHERE v = 0 AND level = 0 AND pred = 0) - 1) + abs((SELECT count(*) FROM bad WHERE level = 0 OR pred = v) - 1))::BIGINT AS violations
  UNION ALL SELECT 'parent edge', count(*) FROM bad WHERE v <> 0 AND NOT EXISTS (SELECT 1 FROM e WHERE e.src = bad.pred AND e.dst = bad.v)
  UNION ALL SELECT 'one level below parent', count(*) FROM bad LEFT JOIN bad p ON p.v = bad.pred WHERE bad.v <> 0 AND bad.level IS DISTINCT FROM p.level + 1
  UNION ALL SELECT 'edge spans one level', count(*) FROM ends WHERE abs(a - b) > 1
  UNION ALL SELECT 'component covered', count(*) FROM ends WHERE b IS NULL""")


@query("validate_corrupt", _CORRUPT)
def _(spark, d):
    tree = plain.parents_global_min(graph(spark, d, "geo"), levels(spark, d, "geo"), 0).where("v % 50 <> 11")
    broken = tree.select("v", F.when(F.col("v") % 50 == 7, F.col("level") + 1).otherwise(F.col("level")).alias("level"), F.when(F.col("v") % 50 == 9, 1).otherwise(F.col("pred")).cast("long").alias("pred"))
    return measures.validate(graph(spark, d, "geo"), broken, 0)


# ---- applications

def _components_sql(gid: str, cap: int) -> str:
    return f"WITH RECURSIVE {sql.simple(gid)}, w(v, c) AS (SELECT DISTINCT src, src FROM e UNION SELECT e.dst, w.c FROM w JOIN e ON e.src = w.v WHERE e.dst > w.c) SELECT v, min(c) AS component FROM w GROUP BY v"


QUERIES["components_geo"] = lambda spark, d: apps.components(tuples(spark, d, "geo"))
QUERIES["components_cc"] = lambda spark, d: apps.components(tuples(spark, d, "cc"))
QUERIES["components_dup"] = lambda spark, d: apps.components(tuples(spark, d, "dup"))
ORACLE_SQL["components_geo"] = f"WITH RECURSIVE {sql.simple('geo')}, w(v, c, n) AS (SELECT r_regionkey::BIGINT, r_regionkey::BIGINT, 0 FROM region UNION SELECT e.dst, w.c, n + 1 FROM w JOIN e ON e.src = w.v WHERE n < 4) SELECT v, min(c) AS component FROM w GROUP BY v"
ORACLE_SQL["components_cc"] = _components_sql("cc", 40)
ORACLE_SQL["components_dup"] = f"WITH RECURSIVE {sql.simple('dup')}, w(v, c) AS (SELECT DISTINCT src, src FROM e UNION SELECT e.dst, w.c FROM w JOIN e ON e.src = w.v) SELECT v, min(c) AS component FROM w GROUP BY v"


for _gid in ("op", "uk", "rmat8"):

    @query(f"bipartite_{_gid}", sql.with_levels(_gid, "SELECT count(*) AS odd_edges FROM e JOIN levels a ON a.v = src JOIN levels b ON b.v = dst WHERE a.level % 2 = b.level % 2 AND src < dst"))
    def _(spark, d, g=_gid):
        return spark.createDataFrame([(apps.odd_edges(graph(spark, d, g), levels(spark, d, g)),)], "odd_edges long")


@query("eccentricity_geo", _many("geo", SEARCHES, "SELECT root, max(level) AS eccentricity FROM many GROUP BY 1"))
def _(spark, d):
    return apps.eccentricities(graph(spark, d, "geo"), plain.sample_roots(graph(spark, d, "geo"), SEARCHES))


@query(
    "diameter_bounds_geo",
    f"""WITH RECURSIVE {sql.simple("geo")}, {sql.walked()}, far AS (SELECT v, level FROM levels ORDER BY level DESC, v LIMIT 1),
    walk2(v, level) AS (SELECT v, 0 FROM far UNION SELECT e.dst, level + 1 FROM walk2 JOIN e ON e.src = walk2.v WHERE level < 12),
    second AS (SELECT max(level) AS n FROM (SELECT v, min(level) AS level FROM walk2 GROUP BY v))
    SELECT greatest(level, n) AS lower_bound, 2 * least(level, n) AS upper_bound FROM far, second""",
)
def _(spark, d):
    return spark.createDataFrame([apps.diameter_bounds(graph(spark, d, "geo"), 0)], "lower_bound int, upper_bound int")


@query("max_flow_nation", "SELECT count(*) AS flow FROM customer WHERE c_nationkey = 3")
def _(spark, d):
    """Unit edges from a nation to its customers and from them to one sink: the flow is the number of customers."""
    customers = graphs.load_table(spark, d, "customer").where("c_nationkey = 3").select("c_custkey")
    pipes = customers.select(F.lit(-1).cast("long").alias("src"), F.col("c_custkey").alias("dst")).unionAll(customers.select(F.col("c_custkey").alias("src"), F.lit(-2).cast("long").alias("dst")))
    return spark.createDataFrame([(apps.max_flow(pipes, -1, -2),)], "flow long")


# ---- streams

@query("stream_edges_window", "SELECT time_bucket(INTERVAL '1 day', ts) AS window_start, user_id AS src, count(*) AS edges FROM events GROUP BY 1, 2")
def _(spark, d):
    return streams.run_to_end(streams.window_counts(streams.edges_stream(spark, d), "1 day"))


@query(
    "stream_sliding",
    "SELECT time_bucket(INTERVAL '12 hours', ts) - x * INTERVAL '12 hours' AS window_start, user_id AS src, count(*) AS edges FROM events, (SELECT unnest([0, 1]) AS x) GROUP BY 1, 2",
)
def _(spark, d):
    return streams.run_to_end(streams.window_counts(streams.edges_stream(spark, d), "1 day", "12 hours"))


@query(
    "stream_session",
    """SELECT min(ts) AS session_start, src, count(*) AS edges FROM (SELECT *, sum(fresh) OVER (PARTITION BY src ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS nth FROM (
       SELECT event_id, ts, user_id AS src, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL '6 hours' THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY src, nth""",
)
def _(spark, d):
    return streams.run_to_end(streams.session_counts(streams.edges_stream(spark, d), "6 hours"))


@query("stream_dedup_watermark", "SELECT DISTINCT user_id AS src, CAST(props->>'$.k' AS BIGINT) AS dst FROM events")
def _(spark, d):
    kept_rows = streams.run_to_end(streams.distinct_edges(streams.edges_stream(spark, d), late="3650 days"), mode="append")
    return kept_rows.select("src", "dst")


@query(
    "stream_late_rows",
    """SELECT event_id, ts, src, dst FROM (SELECT event_id, ts, user_id AS src, CAST(props->>'$.k' AS BIGINT) AS dst,
       max(ts) OVER (PARTITION BY user_id ORDER BY event_id * 7919 % 1000003 ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS newest FROM events) WHERE ts < newest - INTERVAL '1 hour'""",
)
def _(spark, d):
    rows = streams.run_to_end(streams.edges_stream(spark, d), mode="append")
    return streams.late_rows(rows, arrival="event_id * 7919 % 1000003").select("event_id", "ts", "src", "dst")


@query("stream_incremental_levels", sql.with_levels("uk", _LEVELS))
def _(spark, d):
    """The events come in three files, a batch each."""
    users = size(spark, d, "uk") and graphs.load_table(spark, d, "events").agg(F.max("user_id").alias("n")).first()["n"] + 1
    folder = _scratch(spark)
    graphs.load_table(spark, d, "events").repartition(3, "event_id").write.parquet(folder)
    stream = streams.edges_stream(spark, folder, pattern="*.parquet").select("src", (F.col("dst") + users).alias("dst"))
    return streams.IncrementalLevels(spark, 0).follow(stream)


# ---- sources and sinks

def _scratch(spark: SparkSession) -> str:
    ensure_checkpoint_dir(spark)
    return f"{spark.sparkContext.getCheckpointDir()}/edges-{uuid.uuid4().hex}"


for _fmt, _name in (("parquet", "io_parquet_roundtrip"), ("csv", "io_csv_edges"), ("text", "io_text_edge_list"), ("json", "io_json_edges"), ("orc", "io_orc_roundtrip")):

    @query(_name, sql.EDGES["ps"])
    def _(spark, d, fmt=_fmt):
        path = _scratch(spark)
        graphs.write_edges(tuples(spark, d, "ps"), path, fmt)
        return graphs.read_edges(spark, path, fmt)


@query("io_pruned_grid_column", f"WITH {sql.simple('ps')}, nb AS (SELECT {_nb('ps', 4)} AS nb) SELECT ((dst // nb) % 2 * 2 + src // (nb * 2))::INT AS cell, count(*) AS edges FROM e, nb WHERE src // (nb * 2) = 1 GROUP BY 1")
def _(spark, d):
    path = _scratch(spark)
    own = gridded(spark, d, "ps", 2, 2)
    placed = own.adjacency.withColumn("cell", own.layout.number(F.col("cell"))).withColumn("gj", F.col("cell") % 2)
    placed.sortWithinPartitions("cell", "key").write.partitionBy("gj").parquet(path)
    return spark.read.parquet(path).where("gj = 1").groupBy("cell").agg(F.sum(F.size("targets").cast("long")).alias("edges"))


@query("io_generator_source", sql.rmat(9))
def _(spark, d):
    generator.register(spark)
    return spark.read.format("rmat").option("scale", 9).option("partitions", 3).load()


# ---- joins

@query("join_semi_component", sql.with_levels("geo", "SELECT src, dst FROM t WHERE src IN (SELECT v FROM levels)"))
def _(spark, d):
    return tuples(spark, d, "geo").join(levels(spark, d, "geo").select(F.col("v").alias("src")), "src", "left_semi").select("src", "dst")


@query("join_anti_unvisited", sql.with_levels("geo", "SELECT src, dst FROM t WHERE src NOT IN (SELECT v FROM levels)"))
def _(spark, d):
    return tuples(spark, d, "geo").join(levels(spark, d, "geo").select(F.col("v").alias("src")), "src", "left_anti").select("src", "dst")


@query("join_broadcast_frontier", sql.with_levels("op", "SELECT e.src, e.dst FROM e JOIN levels ON v = src WHERE level = 2"))
def _(spark, d):
    front = levels(spark, d, "op").where("level = 2").select(F.col("v").alias("src"))
    front = F.broadcast(front) if front.count() <= BROADCAST_ROWS else front
    return graph(spark, d, "op").join(front, "src").select("src", "dst")


@query("join_range_cumul", f"{_FRONT}, {_SCAN} SELECT i, k FROM (SELECT unnest(range((SELECT sum(degree)::BIGINT FROM deg))) AS i) u JOIN scan ON i >= before AND i < before + degree")
def _(spark, d):
    """Each unit's vertex by range: ranges and units meet in equal cells of 64 units, then the range is checked."""
    scanned = settled(kernel.exclusive_scan(_frontier(spark, d)))
    total = scanned.agg(F.sum("degree").alias("n")).first()["n"]
    spread = scanned.where("degree > 0").withColumn("cell", F.explode(F.sequence(F.floor(F.col("before") / 64), F.floor((F.col("before") + F.col("degree") - 1) / 64))))
    units = spark.range(total).select(F.col("id").alias("i"), F.floor(F.col("id") / 64).alias("cell"))
    return units.join(spread, "cell").where("i >= before and i < before + degree").select("i", "k")


@query("join_full_outer_diff", sql.with_levels("op", "SELECT v, coalesce(a, -1) AS a, coalesce(b, -1) AS b FROM (SELECT v, level AS a FROM levels WHERE v % 3 <> 0) FULL JOIN (SELECT v, level + (v % 5 = 0)::INT AS b FROM levels) USING (v) WHERE a IS DISTINCT FROM b"))
def _(spark, d):
    found = levels(spark, d, "op")
    return measures.compare(found.where("v % 3 <> 0"), found.select("v", (F.col("level") + (F.col("v") % 5 == 0).cast("int")).alias("level"))).fillna(-1)


@query("join_self_copurchase", "SELECT a.l_partkey AS src, b.l_partkey AS dst, count(*) AS orders FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND b.l_linenumber = a.l_linenumber + 1 GROUP BY 1, 2")
def _(spark, d):
    """Parts of neighbouring lines of an order: a self-join on the line number, not all pairs of an order."""
    lines = graphs.load_table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey")
    following = lines.select("l_orderkey", (F.col("l_linenumber") - 1).alias("l_linenumber"), F.col("l_partkey").alias("dst"))
    return lines.join(following, ["l_orderkey", "l_linenumber"]).groupBy(F.col("l_partkey").alias("src"), "dst").agg(F.count("*").alias("orders"))


@query(
    "join_temporal_valid",
    "SELECT l_orderkey AS src, l_partkey AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey AND l_shipdate >= o_orderdate AND l_shipdate < o_orderdate + INTERVAL 30 DAY",
)
def _(spark, d):
    orders = graphs.load_table(spark, d, "orders").select("o_orderkey", "o_orderdate")
    near = (F.col("l_orderkey") == F.col("o_orderkey")) & (F.col("l_shipdate") >= F.col("o_orderdate")) & (F.col("l_shipdate") < F.col("o_orderdate") + F.expr("INTERVAL 30 DAYS"))
    return graphs.load_table(spark, d, "lineitem").join(orders, near).select(F.col("l_orderkey").alias("src"), F.col("l_partkey").alias("dst"))


# ---- aggregations, windows, order, sets

@query("agg_min_by_parent", sql.with_levels("ps", "SELECT e.dst AS v, min(level) AS level, min_by(src, level::BIGINT * 1000000000 + src)::BIGINT AS pred FROM e JOIN levels ON levels.v = src GROUP BY 1"))
def _(spark, d):
    return graph(spark, d, "ps").join(levels(spark, d, "ps").withColumnRenamed("v", "src"), "src").groupBy(F.col("dst").alias("v")).agg(F.min("level").alias("level"), F.min_by("src", F.struct("level", "src")).alias("pred"))


@query("agg_distinct_pairs", _traffic("ps", 2, 2, f"SELECT level, count(DISTINCT (sender, receiver)) AS pairs FROM ({sql.fold('history', 2)}) GROUP BY 1"))
def _(spark, d):
    return _fold(spark, d, "ps", 2, 2, "history").groupBy("level").agg(F.count_distinct("sender", "receiver").alias("pairs"))


@query("agg_degree_percentiles", f"WITH {sql.simple('op')}, g AS (SELECT count(*) AS degree FROM e GROUP BY src) SELECT quantile_disc(degree, 0.5) AS p50, quantile_disc(degree, 0.9) AS p90, quantile_disc(degree, 0.99) AS p99, max(degree) AS largest FROM g")
def _(spark, d):
    counted = prepare.degrees(graph(spark, d, "op"))
    return counted.selectExpr(*(f"percentile_disc({p}) WITHIN GROUP (ORDER BY degree) AS {n}" for p, n in ((0.5, "p50"), (0.9, "p90"), (0.99, "p99"))), "max(degree) AS largest").select(*(F.col(c).cast("long").alias(c) for c in ("p50", "p90", "p99", "largest")))


@query("win_exclusive_scan", f"WITH {sql.simple('ps')}, g AS (SELECT src AS v, count(*) AS degree FROM e GROUP BY src) SELECT v % 8 AS class, v, coalesce(sum(degree) OVER (PARTITION BY v % 8 ORDER BY v ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS before FROM g")
def _(spark, d):
    order = Window.partitionBy("class").orderBy("v").rowsBetween(Window.unboundedPreceding, -1)
    return prepare.degrees(graph(spark, d, "ps")).withColumn("class", F.col("v") % 8).select("class", "v", F.coalesce(F.sum("degree").over(order), F.lit(0)).alias("before"))


@query("win_first_per_target", f"WITH {sql.simple('ps')} SELECT src, dst FROM (SELECT src, dst, row_number() OVER (PARTITION BY dst ORDER BY src) AS nth FROM e) WHERE nth = 1")
def _(spark, d):
    return graph(spark, d, "ps").withColumn("nth", F.row_number().over(Window.partitionBy("dst").orderBy("src"))).where("nth = 1").select("src", "dst")


_SIZES = "sizes AS (SELECT level, count(*) AS n FROM levels GROUP BY 1)"


@query("win_lag_frontier_growth", sql.with_levels("op", f", {_SIZES} SELECT level, n, n - lag(n, 1, 0) OVER (ORDER BY level) AS growth FROM sizes"))
def _(spark, d):
    sizes = levels(spark, d, "op").groupBy("level").agg(F.count("*").alias("n"))
    return sizes.withColumn("growth", F.col("n") - F.lag("n", 1, 0).over(Window.orderBy("level")))


@query("win_cumulative_visited", sql.with_levels("op", f", {_SIZES} SELECT level, sum(n) OVER (ORDER BY level)::BIGINT AS visited FROM sizes"))
def _(spark, d):
    sizes = levels(spark, d, "op").groupBy("level").agg(F.count("*").alias("n"))
    return sizes.select("level", F.sum("n").over(Window.orderBy("level")).alias("visited"))


@query("win_degree_ntile", f"WITH {sql.simple('ps')}, g AS (SELECT src AS v, count(*) AS degree FROM e GROUP BY src) SELECT v, degree, ntile(4) OVER (PARTITION BY v % 4 ORDER BY degree, v) AS quarter, rank() OVER (PARTITION BY v % 4 ORDER BY degree) AS place FROM g")
def _(spark, d):
    part = Window.partitionBy(F.col("v") % 4)
    return prepare.degrees(graph(spark, d, "ps")).select("v", "degree", F.ntile(4).over(part.orderBy("degree", "v")).alias("quarter"), F.rank().over(part.orderBy("degree")).alias("place"))


@query("topk_degree", f"WITH {sql.simple('op')} SELECT src AS v, count(*) AS degree FROM e GROUP BY src ORDER BY degree DESC, v LIMIT 20")
def _(spark, d):
    return prepare.degrees(graph(spark, d, "op")).orderBy(F.desc("degree"), "v").limit(20)


@query("set_union_frontier", sql.with_levels("op", "SELECT v FROM levels WHERE level = 2 UNION SELECT v FROM levels WHERE level IN (2, 3)"))
def _(spark, d):
    found = levels(spark, d, "op")
    return found.where("level = 2").select("v").union(found.where("level in (2, 3)").select("v")).distinct()


@query("set_intersect_wasted", sql.with_levels("op", "SELECT DISTINCT e.dst AS v FROM e JOIN levels a ON a.v = e.src AND a.level = 3 INTERSECT SELECT v FROM levels WHERE level <= 3"))
def _(spark, d):
    found = levels(spark, d, "op")
    reached = graph(spark, d, "op").join(found.where("level = 3").select(F.col("v").alias("src")), "src", "left_semi").select(F.col("dst").alias("v"))
    return reached.intersect(found.where("level <= 3").select("v"))


@query("set_except_unvisited", sql.with_levels("op", "SELECT DISTINCT e.dst AS v FROM e JOIN levels a ON a.v = e.src AND a.level = 3 EXCEPT SELECT v FROM levels WHERE level <= 3"))
def _(spark, d):
    found = levels(spark, d, "op")
    reached = graph(spark, d, "op").join(found.where("level = 3").select(F.col("v").alias("src")), "src", "left_semi").select(F.col("dst").alias("v"))
    return reached.subtract(found.where("level <= 3").select("v"))


@query("set_except_all_diff", f"SELECT src, dst FROM ({sql.EDGES['ps']}) EXCEPT ALL SELECT DISTINCT src, dst FROM ({sql.EDGES['ps']})")
def _(spark, d):
    every = tuples(spark, d, "ps")
    return every.exceptAll(every.distinct())


# ---- functions

@query("fn_bit_ops", f"WITH {sql.simple('ps')} SELECT v, v // 32 AS word, 1::BIGINT << (v % 32) AS mask, bit_count(v)::INT AS ones FROM (SELECT DISTINCT src AS v FROM e)")
def _(spark, d):
    v = graph(spark, d, "ps").select(F.col("src").alias("v")).distinct()
    return v.selectExpr("v", "v div 32 AS word", "shiftleft(CAST(1 AS BIGINT), CAST(v % 32 AS INT)) AS mask", "bit_count(v) AS ones")


@query("fn_array_adjacency", f"WITH {sql.simple('ps')} SELECT src AS v, count(*) AS degree, min(dst)::BIGINT AS first_target, sum((dst % 2 = 0)::INT)::BIGINT AS even_targets FROM e GROUP BY 1")
def _(spark, d):
    lists = layout.build(graph(spark, d, "ps"), layout.ModuloLayout(2), chunk=1 << 20).adjacency
    return lists.select(F.col("key").alias("v"), F.size("targets").cast("long").alias("degree"), F.array_min("targets").alias("first_target"), F.size(F.filter("targets", lambda x: x % 2 == 0)).cast("long").alias("even_targets"))


@query("fn_json_key", "SELECT CAST(props->>'$.k' AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")
def _(spark, d):
    return graphs.load_table(spark, d, "events").groupBy(F.get_json_object("props", "$.k").cast("long").alias("k")).agg(F.count("*").alias("n"))


@query("fn_url_host", "SELECT regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, count(*) AS pages FROM pages GROUP BY 1")
def _(spark, d):
    return graphs.load_table(spark, d, "pages").groupBy(F.parse_url("url", F.lit("HOST")).alias("host")).agg(F.count("*").alias("pages"))


@query("fn_date_bucket_edges", "SELECT date_trunc('month', o_orderdate)::TIMESTAMP AS month, count(*) AS edges FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY 1")
def _(spark, d):
    orders = graphs.load_table(spark, d, "orders").select("o_orderkey", F.date_trunc("month", "o_orderdate").alias("month"))
    return graphs.load_table(spark, d, "lineitem").select("l_orderkey").join(orders, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("month").agg(F.count("*").alias("edges"))


@query(
    "fn_cosine_pairs",
    """SELECT a.vec_id AS src, b.vec_id AS dst, round(list_sum([p[1] * p[2] FOR p IN list_zip(a.e, b.e)]) / (sqrt(list_sum([x * x FOR x IN a.e])) * sqrt(list_sum([x * x FOR x IN b.e]))), 4) AS cosine
    FROM (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings) a JOIN (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings) b ON b.vec_id = a.vec_id + 1""",
)
def _(spark, d):
    vectors = graphs.load_table(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    total = lambda x: F.aggregate(x, F.lit(0.0), lambda a, b: a + b)
    pairs = vectors.join(vectors.select((F.col("vec_id") - 1).alias("vec_id"), F.col("e").alias("f")), "vec_id")
    dot = total(F.zip_with("e", "f", lambda a, b: a * b))
    norm = F.sqrt(total(F.transform("e", lambda a: a * a))) * F.sqrt(total(F.transform("f", lambda a: a * a)))
    return pairs.select(F.col("vec_id").alias("src"), (F.col("vec_id") + 1).alias("dst"), F.round(dot / norm, 4).alias("cosine"))


@query("udf_sql_grid_cell", f"WITH {sql.simple('ps')}, n AS (SELECT (SELECT count(*) FROM part) + (SELECT count(*) FROM supplier) AS n), nb AS (SELECT (n + 3) // 4 AS nb FROM n) SELECT src, dst, (dst // nb) % 2 * 2 + src // (nb * 2) AS cell, (dst // nb) % 2 * 2 + dst // (nb * 2) AS owner FROM e, nb")
def _(spark, d):
    register_sql(spark)
    n = size(spark, d, "ps")
    return graph(spark, d, "ps").selectExpr("src", "dst", f"grid_cell(src, dst, {n}L, 2L, 2L) AS cell", f"owner_cell(dst, {n}L, 2L, 2L) AS owner")


@query("udtf_edge_work", f"{_FRONT}, {_SCAN}, {_UNITS} SELECT i // 4 AS unit, i, k, j FROM units")
def _(spark, d):
    """The same mapping by a table function over a frontier's degrees, for one frontier that fits a row."""
    udx.register_udtfs(spark)
    front = _frontier(spark, d).groupBy().agg(F.transform(F.array_sort(F.collect_list(F.struct("k", "degree"))), lambda x: x["degree"].cast("int")).alias("degrees"))
    front.createOrReplaceTempView("edge_work_frontier")
    return spark.sql("SELECT w.* FROM edge_work_frontier f, LATERAL edge_work(f.degrees, 4) w")


@query("udtf_unpack_bits", f"WITH {sql.simple('op')} SELECT DISTINCT src AS v FROM e")
def _(spark, d):
    udx.register_udtfs(spark)
    packed = _indices(spark, d).groupBy("message").agg(F.bitmap_construct_agg("index").alias("bits"))
    packed.createOrReplaceTempView("packed_messages")
    return spark.sql("SELECT u.v FROM packed_messages p, LATERAL unpack_bits(p.bits, p.message * 4096L) u")


@query("udaf_harmonic", f"WITH {sql.simple('op')} SELECT src % 4 AS class, round(count(*) / sum(1.0 / degree), 6) AS mean FROM (SELECT src, count(*) AS degree FROM e GROUP BY src) GROUP BY 1")
def _(spark, d):
    """The built-in expression beside a pandas aggregate; both are compared, the built-in one is returned."""
    rates = prepare.degrees(graph(spark, d, "op")).select((F.col("v") % 4).alias("class"), F.col("degree").cast("double").alias("x"))

    @F.pandas_udf("double")
    def by_pandas(x: pd.Series) -> float:
        return float(len(x) / np.sum(1.0 / x.to_numpy()))

    both = rates.groupBy("class").agg(by_pandas("x").alias("other")).join(rates.groupBy("class").agg(measures.harmonic_mean(F.col("x")).alias("mean")), "class")
    return both.select("class", F.when(F.abs(F.col("mean") - F.col("other")) < 1e-9, F.round("mean", 6)).alias("mean"))


__all__ = ["ORACLE_SQL", "QUERIES", "star_components"]
