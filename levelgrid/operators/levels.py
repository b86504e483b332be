"""Level-synchronous search without a grid: the engine's plain form, one for many roots at once, and a recursive-SQL one.

The edges are placed once by a hash of their source, in order and in chunks.  A level joins its frontier to them
in place, reads the stretches of keys that the frontier touches, and sends each discovered vertex to its place: one
exchange, of vertices, repeats removed before.  Known vertices are left out by one aggregation in place.

In an undirected graph a neighbour of level L lies in level L - 1, L or L + 1, so a new vertex is told
from known ones by the last two levels alone: state per level does not grow with the search.  For directed
edges all earlier levels are asked.

Many roots share one loop: the roots that reach a vertex in a level are the bits of 64-bit masks, so the searches
share scans, joins and exchanges, and a vertex that many reach at once is one row.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from levelgrid.plans.layout import PLACED, PlacedGraph, compressed, held_in_place
from levelgrid.plans.state import held, settled

#: slices of a result are gathered in one frame when there are so many
SLICES = 32


def by_source(graph: DataFrame, chunk: int = 4096) -> PlacedGraph:
    """The edges placed for plain searches; several searches can share it."""
    spark = graph.sparkSession
    tasks = int(spark.conf.get("spark.sql.shuffle.partitions"))
    with held(spark, PLACED):
        placed = graph.select(F.col("src").alias("key"), F.col("dst").alias("value")).repartition(tasks, "key")
        return held_in_place(compressed(placed, chunk=chunk), None, tasks)


def _in_place(placed: PlacedGraph) -> dict[str, str]:
    """Settings under which what is dealt by a vertex meets the edges where they are."""
    return PLACED | {"spark.sql.shuffle.partitions": str(placed.tasks)}


def _gathered(slices: list[DataFrame], recent: int = 2) -> list[DataFrame]:
    """Older slices as one, so that the plan does not grow with the number of levels."""
    if len(slices) < SLICES + recent:
        return slices
    return [settled(reduce(DataFrame.unionAll, slices[:-recent])), *slices[-recent:]]


def bfs_levels(graph: DataFrame | PlacedGraph, root: int, max_level: int | None = None, symmetric: bool = True, target: int | None = None) -> DataFrame:
    """(v, level) of all vertices within max_level hops of the root; stops early once `target` has a level."""
    placed = graph if isinstance(graph, PlacedGraph) else by_source(graph)
    spark = placed.adjacency.sparkSession
    with held(spark, _in_place(placed)):
        found = [settled(spark.range(root, root + 1).select(F.col("id").alias("key")).repartition(placed.tasks, "key").withColumn("level", F.lit(0)))]
        blocks, level, n = None, 0, 1
        while n and (max_level is None or level < max_level):
            level += 1
            near = found[-1].select("key").join(placed.touched(blocks).hint("merge"), "key").select(F.explode("targets").alias("key"))
            rows = near.distinct().select("key", F.lit(0).alias("old"))
            for known in found[-2:] if symmetric else found:
                rows = rows.unionAll(known.select("key", F.lit(1).alias("old")))
            fresh = rows.groupBy("key").agg(F.max("old").alias("old")).where("old = 0").select("key", F.lit(level).alias("level"))
            seen = Observation()
            fresh = settled(fresh.observe(seen, F.count("*").alias("n"), F.count(F.when(F.col("key") == target, 1)).alias("hits"), placed.watched(F.col("key")).alias("blocks")))
            told = seen.get
            n, blocks = told["n"], bytes(told["blocks"])
            if n:
                found = _gathered([*found, fresh]) if symmetric else [*found, fresh]
            if target is not None and told["hits"]:
                break
    return reduce(DataFrame.unionAll, found).select(F.col("key").alias("v"), "level")


def fill_unreached(levels: DataFrame, n: int) -> DataFrame:
    """All ids below n; level -1 where the search did not come."""
    every = levels.sparkSession.range(n).select(F.col("id").alias("v"))
    return every.join(levels.select("v", "level"), "v", "left").select("v", F.coalesce("level", F.lit(-1)).alias("level"))


def bfs_recursive(spark: SparkSession, graph: DataFrame, root: int, depth: int) -> DataFrame:
    """The same levels by recursive SQL, for cross-checks on small graphs: it lists walks, so depth is capped."""
    graph.createOrReplaceTempView("recursive_edges")
    return spark.sql(
        f"""WITH RECURSIVE walk(v, level) AS (
              SELECT CAST({root} AS BIGINT), 0
              UNION ALL
              SELECT e.dst, walk.level + 1 FROM walk JOIN recursive_edges e ON e.src = walk.v WHERE walk.level < {depth})
            SELECT v, min(level) AS level FROM walk GROUP BY v"""
    )


def parents_global_min(graph: DataFrame, levels: DataFrame, root: int) -> DataFrame:
    """(v, level, pred): of a vertex's neighbours one level above, the smallest; the root is its own."""
    up = levels.select(F.col("v").alias("src"), (F.col("level") + 1).alias("level"))
    told = graph.join(up, "src").select(F.col("dst").alias("v"), "level", "src").join(levels, ["v", "level"], "left_semi")
    least = told.groupBy("v", "level").agg(F.min("src").alias("pred"))
    start = levels.where(F.col("level") == 0).select("v", "level", F.col("v").alias("pred"))
    return start.unionAll(least)


def shortest_path(tree: DataFrame, target: int) -> DataFrame:
    """(step, v) from the root to the target along a tree (v, level, pred); one look-up a step, none if not reached."""
    steps, v = [], target
    while True:
        row = tree.where(F.col("v") == v).select("level", "pred").first()
        if row is None:
            return tree.sparkSession.createDataFrame([], "step int, v long")
        steps.append((row["level"], v))
        if row["pred"] == v:
            return tree.sparkSession.createDataFrame(sorted(steps), "step int, v long")
        v = row["pred"]


def bfs_masks(graph: DataFrame | PlacedGraph, roots: list[int], max_level: int | None = None) -> DataFrame:
    """(v, word, mask, level): bit b of a mask says that root number 64 * word + b is `level` hops from v."""
    placed = graph if isinstance(graph, PlacedGraph) else by_source(graph)
    spark, words = placed.adjacency.sparkSession, range(-(-len(roots) // 64))
    masks = [f"m{w}" for w in words]
    every = lambda form: [F.expr(form.format(m)).alias(m) for m in masks]
    some = " or ".join(f"{m} <> 0" for m in masks)
    with held(spark, _in_place(placed)):
        bit = lambda i, w: (1 << i % 64) - (1 << 64 if i % 64 == 63 else 0) if i // 64 == w else 0
        start = spark.createDataFrame([(r, *(bit(i, w) for w in words)) for i, r in enumerate(roots)], ", ".join(["key long", *(f"{m} long" for m in masks)]))
        found = [settled(start.groupBy("key").agg(*every("bit_or({0})")).withColumn("level", F.lit(0)))]
        blocks, level, n = None, 0, len(roots)
        while n and (max_level is None or level < max_level):
            level += 1
            near = found[-1].join(placed.touched(blocks).hint("merge"), "key").select(F.explode("targets").alias("key"), *masks)
            rows = near.groupBy("key").agg(*every("bit_or({0})")).select("key", *masks, *(F.lit(0).cast("long").alias(f"known_{m}") for m in masks))
            for known in found[-2:]:
                rows = rows.unionAll(known.select("key", *(F.lit(0).cast("long").alias(m) for m in masks), *(F.col(m).alias(f"known_{m}") for m in masks)))
            fresh = rows.groupBy("key").agg(*every("bit_or({0}) & ~bit_or(known_{0})")).where(some)
            seen = Observation()
            fresh = settled(fresh.withColumn("level", F.lit(level)).observe(seen, F.count("*").alias("n"), placed.watched(F.col("key")).alias("blocks")))
            told = seen.get
            n, blocks = told["n"], bytes(told["blocks"])
            if n:
                found = _gathered([*found, fresh])
    told = reduce(DataFrame.unionAll, found)
    by_word = F.explode(F.array(*(F.struct(F.lit(w).alias("word"), F.col(m).alias("mask")) for w, m in zip(words, masks)))).alias("w")
    return told.select(F.col("key").alias("v"), "level", by_word).select("v", "w.word", "w.mask", "level").where("mask <> 0")


def bfs_batched(graph: DataFrame | PlacedGraph, roots: DataFrame, max_level: int | None = None) -> DataFrame:
    """(root, v, level) of many searches in one loop; the roots are a short list, a row each."""
    named = [r["root"] for r in roots.select("root").distinct().orderBy("root").collect()]
    if not named:
        return roots.select("root", F.col("root").alias("v"), F.lit(0).alias("level"))
    masks = bfs_masks(graph, named, max_level)
    bits = F.filter(F.sequence(F.lit(0), F.lit(63)), lambda b: F.call_function("shiftright", F.col("mask"), b).bitwiseAND(1) != 0)
    told = masks.select("v", "level", F.explode(F.transform(bits, lambda b: F.col("word") * 64 + b)).alias("nth"))
    return told.select(F.element_at(F.array(*(F.lit(r).cast("long") for r in named)), F.col("nth") + 1).alias("root"), "v", "level")


def sample_roots(graph: DataFrame, k: int = 64, seed: int = 1) -> DataFrame:
    """k vertices with an edge, by a portable hash of the id: the same ones on every run and engine."""
    key = (F.col("root") * 69621 + seed * 16807 + 12345) % 2147483647
    return graph.select(F.col("src").alias("root")).distinct().withColumn("key", key).orderBy("key", "root").limit(k).select("root")
