"""Searches against the hand graph, fixtures of known shape, random graphs and traffic goldens."""

import random
from collections import deque

import numpy as np
import pytest
from pyspark.sql import functions as F

from levelgrid.functions.grid import GridSpec
from levelgrid.operators import codec, measures
from levelgrid.operators import levels as plain
from levelgrid.operators.prepare import symmetrize
from levelgrid.operators.search import _fresh, _once, expanded, folded, search
from levelgrid.plans.layout import PLACED, GridLayout, ModuloLayout, build, grid_property_violations, hash_of, seats, stretches
from levelgrid.plans.state import held
from levelgrid.sources import generator
from levelgrid.sources.graphs import PRIME, rmat_edges

TOY = [(0, 1), (0, 4), (1, 2), (1, 5), (2, 3), (2, 6), (3, 7), (4, 5), (5, 6), (6, 7)]
OWNER_FIRST = [(0, 0, 0), (1, 1, 0), (2, 2, 1), (3, 3, 2), (4, 1, 0), (5, 2, 4), (6, 3, 5), (7, 4, 6)]
SMALLEST = [(0, 0, 0), (1, 1, 0), (2, 2, 1), (3, 3, 2), (4, 1, 0), (5, 2, 1), (6, 3, 2), (7, 4, 3)]
# fold messages of the hand graph: (level, sender, receiver, vertices), cells numbered i*2 + j
FOLD = [(1, 0, 1, 1), (2, 0, 1, 1), (2, 1, 0, 1), (3, 1, 0, 1), (3, 2, 3, 1), (4, 2, 3, 1), (4, 3, 2, 1), (5, 3, 2, 1)]
EXPAND = [(1, 0, 2, 1), (2, 0, 2, 1), (2, 1, 3, 1), (3, 1, 3, 1), (3, 2, 0, 1), (4, 2, 0, 1), (4, 3, 1, 1), (5, 3, 1, 1)]


def graph_of(spark, edges):
    return symmetrize(spark.createDataFrame(edges or [], "src long, dst long"))


def rows(frame):
    return sorted(tuple(r) for r in frame.collect())


def python_levels(edges, root):
    near = {}
    for u, v in edges:
        if u != v:
            near.setdefault(u, set()).add(v)
            near.setdefault(v, set()).add(u)
    level, queue = {root: 0}, deque([root])
    while queue:
        u = queue.popleft()
        for v in near.get(u, ()):
            if v not in level:
                level[v] = level[u] + 1
                queue.append(v)
    return sorted(level.items())


@pytest.fixture(scope="module")
def toy(spark):
    return build(graph_of(spark, TOY), GridLayout(GridSpec(8, 2, 2)))


@pytest.mark.parametrize(
    "options",
    [{}, {"parents": "eager"}, {"codec": "auto"}, {"codec": "list"}, {"codec": "bitmap"}, {"kernel": "arrow"}, {"kernel": "arrow", "group": 4}, {"once": "compact"}, {"state": "bits"}, {"dedup": "level"}, {"dedup": "receiver"}],
    ids=str,
)
def test_hand_graph_variants(toy, options):
    assert rows(search(toy, 0, **options).tree()) == OWNER_FIRST


def test_hand_graph_messages(toy):
    found = search(toy, 0)
    assert rows(found.fold_messages()) == FOLD
    assert rows(found.expand_messages()) == EXPAND
    wasted = measures.wasted_fold(found._all(found.found), found._all(found.fronts))
    assert sum(r["wasted"] for r in wasted.collect()) == 7


def test_smallest_parent_rule(toy):
    assert rows(search(toy, 0, dedup="level", parents="eager", rule="smallest").tree()) == SMALLEST


def test_unknown_variants_are_refused(toy):
    for options in ({"dedup": "none"}, {"rule": "smallest"}, {"codec": "list", "parents": "eager"}):
        with pytest.raises(ValueError):
            search(toy, 0, **options)


@pytest.mark.parametrize("scale,r,c,fold,expand", [(8, 2, 2, {"history": (215, 6), "level": (359, 10), "receiver": (1964, 10)}, (236, 9)), (8, 4, 4, {"history": (540, 72), "level": (776, 101), "receiver": (3064, 101)}, (708, 96))])
def test_traffic_goldens(spark, scale, r, c, fold, expand):
    placed = build(symmetrize(rmat_edges(spark, scale)), GridLayout(GridSpec(1 << scale, r, c)))
    for dedup, told in fold.items():
        found = search(placed, 0, dedup=dedup)
        assert tuple(found.fold_messages().agg(F.sum("vertices"), F.count("*")).first()) == told
        assert tuple(found.expand_messages().agg(F.sum("vertices"), F.count("*")).first()) == expand


def test_one_dimensional_goldens(spark):
    placed = build(symmetrize(rmat_edges(spark, 8)), ModuloLayout(4))
    told = {d: search(placed, 0, dedup=d).fold_messages().agg(F.sum("vertices")).first()[0] for d in ("receiver", "level", "history")}
    assert told == {"receiver": 3090, "level": 771, "history": 536}


SHAPES = {
    "path": [(i, i + 1) for i in range(9)],
    "star": [(0, i) for i in range(1, 50)],
    "complete": [(i, j) for i in range(6) for j in range(i)],
    "two triangles": [(0, 1), (1, 2), (2, 0), (3, 4), (4, 5), (5, 3)],
    "loops and repeats": [(0, 0), (0, 1), (0, 1), (1, 0), (1, 2), (2, 2)],
}


@pytest.mark.parametrize("name", SHAPES)
def test_shapes(spark, name):
    edges = SHAPES[name]
    graph = graph_of(spark, edges)
    n = max(max(e) for e in edges) + 1
    wanted = python_levels(edges, 0)
    assert rows(plain.bfs_levels(graph, 0)) == wanted
    assert rows(search(build(graph, GridLayout(GridSpec(n, 2, 2))), 0).levels()) == wanted


def test_random_graphs(spark):
    draw = random.Random(5)
    for n, m, r, c in ((7, 9, 2, 2), (30, 60, 2, 3), (40, 45, 3, 2)):
        edges = [(draw.randrange(n), draw.randrange(n)) for _ in range(m)]
        graph = graph_of(spark, edges)
        wanted = python_levels(edges, 1)
        placed = build(graph, GridLayout(GridSpec(n, r, c)), chunk=2)
        found = search(placed, 1)
        assert rows(found.levels()) == wanted
        assert rows(search(placed, 1, kernel="arrow").levels()) == wanted
        assert all(r["violations"] == 0 for r in measures.validate(graph, found.tree(), 1).collect())
        assert all(r["violations"] == 0 for r in grid_property_violations(graph, GridSpec(n, r, c)).collect())


def test_root_without_edges_and_empty_graph(spark):
    assert rows(plain.bfs_levels(graph_of(spark, TOY), 99)) == [(99, 0)]
    assert rows(search(build(graph_of(spark, TOY), GridLayout(GridSpec(12, 2, 2))), 11).levels()) == [(11, 0)]
    assert rows(plain.bfs_levels(graph_of(spark, []), 0)) == [(0, 0)]


def executed(frame):
    return frame._jdf.queryExecution().executedPlan().toString()


def test_edges_stay_in_place_and_in_order(spark, toy):
    """An expansion moves and sorts the frontier only; of the adjacency it reads the stretches that are asked for."""
    with held(spark, PLACED):
        front = spark.createDataFrame([(0, 0)], "cell int, key int").repartition(4, "cell")
        joined = front.join(toy.touched(bytes([5]), least=0).hint("merge"), ["cell", "key"]).select("cell", F.explode("targets").alias("value"), "key")
        plan = executed(joined.groupBy("cell", "value").agg(F.min("key")))
    assert plan.count("Exchange") == 1 and plan.count(" Sort ") == 1, plan
    scan = next(x for x in plan.splitlines() if "InMemoryTableScan" in x)
    assert "key#" in scan.split("], [")[1] and " OR " in scan, scan


def test_lists_are_made_by_all_tasks(spark, monkeypatch):
    """Few cells are few tasks: chunks are collected before they are moved there, where they are only put in order."""
    monkeypatch.setattr("levelgrid.plans.layout.held_in_place", lambda frame, *_: frame)
    for layout in (GridLayout(GridSpec(8, 2, 1)), ModuloLayout(2)):
        with held(spark, PLACED):
            plan = executed(build(graph_of(spark, TOY), layout))
        above, below = plan.split("Exchange hashpartitioning(cell", 1)
        assert "Window" not in above and "Aggregate" not in above and "Sort" in above, plan
        assert "Window" in below and "Exchange hashpartitioning(key" in below, plan


def test_chunks_of_hubs(spark):
    """Chunks are sorted, full but for the last, and in order in their cell."""
    star = [(0, i) for i in range(1, 50)] + [(51, 50)]
    placed = build(graph_of(spark, star), ModuloLayout(2), chunk=20).adjacency
    assert [(r["part"], r["targets"]) for r in placed.where("key = 0").orderBy("part").collect()] == [(0, list(range(1, 21))), (1, list(range(21, 41))), (2, list(range(41, 50)))]
    for cell in placed.select("key", "part", F.spark_partition_id().alias("task")).groupBy("task").agg(F.collect_list(F.struct("key", "part")).alias("rows")).collect():
        assert cell["rows"] == sorted(cell["rows"])


def test_stretches():
    assert stretches([3, 4, 9]) == [(3, 4), (9, 9)] and stretches([]) == []
    assert stretches([0, 5, 6, 100], most=2) == [(0, 6), (100, 100)]
    every = sorted(random.Random(1).sample(range(256), 90))
    assert all(any(a <= x <= b for a, b in stretches(every)) for x in every) and len(stretches(every)) <= 8


@pytest.mark.parametrize("codec", [None, "list", "bitmap", "auto"])
def test_one_exchange_a_phase(spark, toy, codec):
    """Rows or packed messages: each phase moves them once, and their receivers take them where they arrive."""
    with held(spark, PLACED):
        front = spark.createDataFrame([(0, 1, 1), (1, 0, 2)], "cell int, key int, value int").repartition(4, "cell").checkpoint()
        found = spark.createDataFrame([(0, 1, 0, 0, 1), (0, 3, 1, 1, 1)], "cell int, value int, key int, owner int, level int").repartition(4, "cell").checkpoint()
        scanned = expanded(front.unionAll(front), toy, codec).join(toy.adjacency.hint("merge"), ["cell", "key"]).select("cell", "key", F.explode("targets").alias("value"))
        expand = executed(_once(scanned, [found, front], "atomic"))
        fold = executed(_fresh(folded(found, toy, codec, True), [found, front], True))
    assert expand.count("Exchange") == 1, expand
    assert fold.count("Exchange") == 1, fold


def test_seats(spark):
    told = spark.range(200).select(F.hash(F.col("id").cast("int")).alias("h")).collect()
    assert [r["h"] for r in told] == [hash_of(i) for i in range(200)]
    for cells in (1, 6, 16, 64):
        assert [hash_of(x) % cells for x in seats(cells)] == list(range(cells))


@pytest.mark.parametrize("nb,indices", [(64, [0, 63]), (100, list(range(100))), (70_000, [0, 1, 32767, 32768, 65535, 65536, 69_999]), (40_000, list(range(0, 40_000, 3)))])
def test_messages_round_trip(spark, nb, indices):
    """Whatever the encoding; short last buckets too."""
    frame = spark.createDataFrame([(k, i) for k in (1, 2) for i in indices], "m int, i long")
    for kind in ("list", "bitmap", "auto"):
        sent = codec.messages(frame, ["m"], "i", nb, kind)
        assert rows(codec.unpack(sent, ["m"], "i")) == sorted((k, i) for k in (1, 2) for i in indices)
        told = sent.groupBy("m").agg(F.first("kind").alias("kind"), F.sum(codec.payload()).alias("bytes")).collect()
        as_list = kind == "list" or (kind == "auto" and len(indices) <= nb // 32)
        assert all(r["kind"] == ("list" if as_list else "bitmap") for r in told)
        assert all(r["bytes"] == (4 * len(indices) if as_list else -(-nb // 64) * 8) for r in told)


@pytest.mark.parametrize("indices", [[3], [40_000], [69_999], [5, 69_998]])
def test_bitmaps_cover_the_whole_block(spark, indices):
    """Buckets without an index are a part of a bitmap, before, between and after the others."""
    frame = spark.createDataFrame([(1, i) for i in indices], "m int, i long")
    sent = codec.messages(frame, ["m"], "i", 70_000, "bitmap")
    assert [tuple(r) for r in sent.orderBy("bucket").select("bucket", F.size("words"), "n").collect()] == [(0, 512, len(indices)), (1, 512, len(indices)), (2, 70, len(indices))]
    assert rows(codec.unpack(sent, ["m"], "i")) == [(1, i) for i in indices]


@pytest.mark.parametrize("start", [0, 33_000, 66_000])
def test_auto_takes_the_whole_bitmap_or_the_list(spark, start):
    """Above the switch a message that lies in one bucket is as long as any bitmap; at the switch it is a list without other buckets."""
    for many, told in ((2_187, [(start >> 15, "list", 4 * 2_187)]), (2_188, [(0, "bitmap", 512 * 8), (1, "bitmap", 512 * 8), (2, "bitmap", 70 * 8)])):
        frame = spark.range(start, start + many).selectExpr("1 as m", "id as i")
        sent = codec.messages(frame, ["m"], "i", 70_000, "auto")
        assert rows(sent.select("bucket", "kind", codec.payload())) == told
        assert rows(codec.unpack(sent, ["m"], "i")) == [(1, i) for i in range(start, start + many)]


def test_bytes_of_blocks_of_many_buckets(spark):
    """A block of 70,000 places takes 1,094 words as a bitmap, however few of them are set; a list takes what it holds."""
    far = [(u * 30_000, v * 30_000) for u, v in TOY]
    placed = build(graph_of(spark, far), GridLayout(GridSpec(280_000, 2, 2)))
    for kind, size in (("bitmap", lambda n: 1_094 * 8), ("auto", lambda n: 4 * n)):
        found = search(placed, 0, codec=kind)
        assert rows(found.levels()) == python_levels(far, 0)
        assert all(r["bytes"] == size(r["vertices"]) for r in found.sent_messages().collect())


def test_one_exchange_a_phase_in_blocks_of_many_buckets(spark):
    with held(spark, PLACED):
        placed = build(graph_of(spark, TOY), GridLayout(GridSpec(280_000, 2, 2)))
        front = spark.createDataFrame([(0, 1, 1), (1, 0, 2)], "cell int, key int, value int").repartition(4, "cell").checkpoint()
        assert executed(expanded(front, placed, "bitmap")).count("Exchange") == 1


def test_packed_messages_as_they_are_sent(toy):
    for kind in ("bitmap", "auto"):
        sent = search(toy, 0, codec=kind).sent_messages()
        told = {p: sorted(tuple(r)[1:4] + (r["vertices"],) for r in sent.where(F.col("phase") == p).collect()) for p in ("fold", "expand")}
        assert told == {"fold": FOLD, "expand": EXPAND}
    with pytest.raises(ValueError):
        search(toy, 0).sent_messages()


def test_packed_messages_on_the_modulo_layout(spark):
    graph = graph_of(spark, TOY)
    assert rows(search(build(graph, ModuloLayout(3, 8)), 0, codec="auto").levels()) == python_levels(TOY, 0)
    unsized = build(graph, ModuloLayout(3))
    assert rows(search(unsized, 0, state="bits").levels()) == python_levels(TOY, 0)
    with pytest.raises(ValueError):
        search(unsized, 0, codec="bitmap")


def test_many_roots_at_once(spark):
    draw = random.Random(3)
    edges = [(draw.randrange(90), draw.randrange(90)) for _ in range(110)]
    graph = graph_of(spark, edges)
    roots = sorted({v for e in edges for v in e if e[0] != e[1]})
    assert len(roots) > 64
    told = plain.bfs_batched(graph, spark.createDataFrame([(r,) for r in roots], "root long"))
    assert rows(told) == sorted((r, v, level) for r in roots for v, level in python_levels(edges, r))
    assert plain.bfs_batched(graph, spark.createDataFrame([], "root long")).count() == 0


def test_long_paths_keep_short_plans(spark):
    n = 90
    edges = [(i, i + 1) for i in range(n)]
    found = plain.bfs_levels(graph_of(spark, edges), 0)
    assert rows(found) == [(i, i) for i in range(n + 1)]
    assert executed(found).count("Scan ExistingRDD") < 40


def test_searches_share_placed_edges(spark):
    placed = plain.by_source(graph_of(spark, TOY))
    for root in (0, 5):
        assert rows(plain.bfs_levels(placed, root)) == python_levels(TOY, root)
    placed.close()


def test_generator_does_not_repeat_after_its_period():
    first = np.arange(1000, dtype=np.int64)
    a, b = (generator.tuples_of(first + k * (PRIME - 1), 20, 42) for k in (0, 1))
    assert (a[0] != b[0]).mean() > 0.9 and (a[1] != b[1]).mean() > 0.9


def test_limits_and_paths(spark):
    graph = graph_of(spark, TOY)
    assert rows(plain.bfs_levels(graph, 0, max_level=1)) == [(0, 0), (1, 1), (4, 1)]
    tree = plain.parents_global_min(graph, plain.bfs_levels(graph, 0), 0)
    assert rows(plain.shortest_path(tree, 7)) == [(0, 0), (1, 1), (2, 2), (3, 3), (4, 7)]
    assert rows(plain.shortest_path(tree, 70)) == []
    assert rows(plain.fill_unreached(plain.bfs_levels(graph_of(spark, [(0, 1)]), 0), 3)) == [(0, 0), (1, 1), (2, -1)]


def test_directed_search(spark):
    edges = spark.createDataFrame([(0, 1), (1, 2), (2, 0), (3, 0)], "src long, dst long")
    assert rows(plain.bfs_levels(edges, 0, symmetric=False)) == [(0, 0), (1, 1), (2, 2)]


def test_same_result_whatever_the_session(spark, toy):
    for settings in ({"spark.sql.shuffle.partitions": "1"}, {"spark.sql.adaptive.enabled": "false"}, {"spark.sql.shuffle.partitions": "7"}):
        with held(spark, settings):
            assert rows(search(toy, 0).tree()) == OWNER_FIRST


def test_chained_calls(spark):
    from levelgrid.api import GraphSearch

    toy = GraphSearch(spark).from_edges(spark.createDataFrame(TOY, "src long, dst long"))
    assert rows(toy.grid(2, 2).bfs(0).tree()) == OWNER_FIRST
    assert rows(toy.modulo(3).bfs(0).levels()) == rows(toy.levels(0)) == rows(toy.bfs(0).levels())
    assert toy.tuples_traversed(toy.levels(0)) == len(TOY)
    with pytest.raises(ValueError):
        toy.bfs(8)
    with pytest.raises(ValueError):
        GraphSearch(spark).from_edges(spark.createDataFrame(TOY, "src long, dst long"), 5)
    with pytest.raises(ValueError):
        GraphSearch(spark).from_edges(spark.createDataFrame([(1, 2)], "src int, dst int"))


def test_generator_source(spark):
    generator.register(spark)
    wanted = rows(rmat_edges(spark, 6))
    assert rows(spark.read.format("rmat").option("scale", 6).option("partitions", 3).load()) == wanted
    assert wanted == sorted(zip(*(x.tolist() for x in generator.tuples_of(np.arange(16 << 6), 6, 42))))
