"""Edge lists from ordinary tables, from files, and from a recursive-quadrant generator.

Every builder returns input tuples (src BIGINT, dst BIGINT): directed, repeats and loops as they come.
Keys of different tables get disjoint ids by offsets, which are row counts of dense 0-based keys.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from levelgrid.operators.prepare import dense_ids

EDGES = "src long, dst long"


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _size(spark: SparkSession, sf_dir: str, name: str) -> int:
    return load_table(spark, sf_dir, name).count()


def _above(frame: DataFrame, name: str) -> int:
    """One more than the largest value of a column; 0 in an empty table."""
    most = frame.agg(F.max(name).alias("n")).first()["n"]
    return 0 if most is None else most + 1


def edges_from(frame: DataFrame, src: Column, dst: Column, where: Column | None = None) -> DataFrame:
    """Input tuples from any two expressions; the filter and the two columns reach the scan."""
    frame = frame if where is None else frame.where(where)
    return frame.select(src.cast("long").alias("src"), dst.cast("long").alias("dst")).where("src is not null and dst is not null")


def order_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return edges_from(load_table(spark, sf_dir, "lineitem"), F.col("l_orderkey"), F.col("l_partkey") + _size(spark, sf_dir, "orders"))


def part_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return edges_from(load_table(spark, sf_dir, "lineitem"), F.col("l_partkey"), F.col("l_suppkey") + _size(spark, sf_dir, "part"))


def _customer_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = load_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    return load_table(spark, sf_dir, "lineitem").join(orders, F.col("l_orderkey") == F.col("o_orderkey"))


def customer_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return edges_from(_customer_lines(spark, sf_dir), F.col("o_custkey"), F.col("l_partkey") + _size(spark, sf_dir, "customer"))


def customer_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return edges_from(_customer_lines(spark, sf_dir), F.col("o_custkey"), F.col("l_suppkey") + _size(spark, sf_dir, "customer"))


def user_key(spark: SparkSession, sf_dir: str, where: Column | None = None) -> DataFrame:
    events = load_table(spark, sf_dir, "events")
    users = _above(events, "user_id")
    return edges_from(events, F.col("user_id"), F.get_json_object("props", "$.k").cast("long") + users, where)


def geography(spark: SparkSession, sf_dir: str) -> DataFrame:
    regions, nations, customers = (_size(spark, sf_dir, t) for t in ("region", "nation", "customer"))
    nation = edges_from(load_table(spark, sf_dir, "nation"), F.col("n_regionkey"), F.col("n_nationkey") + regions)
    customer = edges_from(load_table(spark, sf_dir, "customer"), F.col("c_nationkey") + regions, F.col("c_custkey") + (regions + nations))
    supplier = edges_from(load_table(spark, sf_dir, "supplier"), F.col("s_nationkey") + regions, F.col("s_suppkey") + (regions + nations + customers))
    return nation.unionAll(customer).unionAll(supplier)


def conversation_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each turn to the next one of its conversation; id = conv_id * width + turn."""
    turns = load_table(spark, sf_dir, "conversations").select("conv_id", "turn").distinct()
    width = _above(turns, "turn")
    following = turns.select("conv_id", (F.col("turn") - 1).alias("turn"))
    return edges_from(turns.join(following, ["conv_id", "turn"]), F.col("conv_id") * width + F.col("turn"), F.col("conv_id") * width + F.col("turn") + 1)


def page_target(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages to the targets of their links, which are numbered in string order after the pages."""
    pages = load_table(spark, sf_dir, "pages")
    found = pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'))).alias("target"))
    numbered = dense_ids(found.select("target").distinct(), "target", "nth")
    return edges_from(found.join(numbered, "target"), F.col("page_id"), F.col("nth") + pages.count())


def document_line(spark: SparkSession, sf_dir: str, shortest: int = 20) -> DataFrame:
    """Documents to each trimmed lower-cased line that two or more of them have."""
    documents = load_table(spark, sf_dir, "documents")
    lines = documents.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.lower(F.trim("line")).alias("line")).where(F.char_length("line") >= shortest).distinct()
    shared = lines.groupBy("line").agg(F.count("*").alias("n")).where("n > 1").select("line")
    return edges_from(lines.join(dense_ids(shared, "line", "nth"), "line"), F.col("doc_id"), F.col("nth") + documents.count())


def vector_label(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vectors to their labels: vectors of one label are two steps apart, without all pairs of them."""
    vectors = load_table(spark, sf_dir, "embeddings")
    return edges_from(vectors, F.col("vec_id"), F.col("label") + vectors.count())


def all_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All foreign keys: region, nation, customer, supplier, part and orders in disjoint blocks of ids."""
    at, total = {}, 0
    for name in ("region", "nation", "customer", "supplier", "part", "orders"):
        at[name] = total
        total += _size(spark, sf_dir, name)
    t = lambda name: load_table(spark, sf_dir, name)
    pieces = [
        edges_from(t("nation"), F.col("n_nationkey") + at["nation"], F.col("n_regionkey")),
        edges_from(t("customer"), F.col("c_custkey") + at["customer"], F.col("c_nationkey") + at["nation"]),
        edges_from(t("supplier"), F.col("s_suppkey") + at["supplier"], F.col("s_nationkey") + at["nation"]),
        edges_from(t("orders"), F.col("o_orderkey") + at["orders"], F.col("o_custkey") + at["customer"]),
        edges_from(t("lineitem"), F.col("l_orderkey") + at["orders"], F.col("l_partkey") + at["part"]),
        edges_from(t("lineitem"), F.col("l_partkey") + at["part"], F.col("l_suppkey") + at["supplier"]),
    ]
    out = pieces[0]
    for piece in pieces[1:]:
        out = out.unionAll(piece)
    return out


#: graph ids; how many ids each uses is told by `vertex_count`
BUILDERS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op": order_part,
    "ps": part_supplier,
    "cp": customer_part,
    "cs": customer_supplier,
    "uk": user_key,
    "geo": geography,
    "cc": conversation_chain,
    "web": page_target,
    "dup": document_line,
    "knn": vector_label,
    "all": all_keys,
}
_TABLES = {"op": ("orders", "part"), "ps": ("part", "supplier"), "cp": ("customer", "part"), "cs": ("customer", "supplier"), "geo": ("region", "nation", "customer", "supplier"), "all": ("region", "nation", "customer", "supplier", "part", "orders")}


def vertex_count(spark: SparkSession, sf_dir: str, gid: str) -> int:
    """Ids of a graph: 0 up to this, used or not."""
    if gid in _TABLES:
        return sum(_size(spark, sf_dir, t) for t in _TABLES[gid])
    row = BUILDERS[gid](spark, sf_dir).agg(F.max(F.greatest("src", "dst")).alias("n")).first()
    return (row["n"] if row["n"] is not None else -1) + 1


# fixed values of the generator: a multiplicative congruential sequence modulo 2**31 - 1
PRIME, STEP, SPREAD, SHIFT = 2147483647, 48271, 69621, 12345
SEED_STEP = 16807


def drift(level: int) -> int:
    """What the state of a level moves by for each time that the sequence has run through."""
    return pow(SPREAD, level + 1, PRIME)


def rmat_edges(spark: SparkSession, scale: int, edge_factor: int = 16, probs=(0.57, 0.19, 0.19, 0.05), seed: int = 42) -> DataFrame:
    """edge_factor * 2**scale tuples over 2**scale vertices: at each of `scale` levels a quadrant is drawn.

    Integer arithmetic only, so any engine gives the same tuples.  The state of level k is the first one
    times STEP**k modulo PRIME, so no level waits for the one before.  After PRIME - 1 tuples the first states
    come again; from then on each level's state is moved by a step of its own, so tuples do not repeat as a sequence.
    """
    cuts = [round(sum(probs[: i + 1]) * PRIME) for i in range(3)]
    total = edge_factor << scale
    ids = spark.range(total)
    lap = F.floor(F.col("id") / (PRIME - 1)) if total > PRIME - 1 else None
    first = ((F.col("id") * SPREAD + (seed * SEED_STEP + SHIFT)) % (PRIME - 1) + 1) * (STEP * SPREAD % PRIME) % PRIME
    ids = ids.select(first.alias("x"), *([] if lap is None else [lap.alias("lap")]))
    src, dst = F.lit(0).cast("long"), F.lit(0).cast("long")
    for k in range(scale):
        state = F.col("x") * pow(STEP, k, PRIME) % PRIME
        state = state if lap is None else (state + F.col("lap") * drift(k)) % PRIME
        bit = 1 << (scale - 1 - k)
        src = src + F.when(state >= cuts[1], bit).otherwise(0)
        dst = dst + F.when(((state >= cuts[0]) & (state < cuts[1])) | (state >= cuts[2]), bit).otherwise(0)
    return ids.select(src.alias("src"), dst.alias("dst"))


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """Edges from Parquet, ORC, JSON, CSV with a header, or text lines `src dst` with # comments."""
    if fmt == "text":
        lines = spark.read.text(path).where(~F.col("value").startswith("#")).select(F.split(F.trim("value"), r"\s+").alias("ids"))
        return edges_from(lines.where(F.size("ids") >= 2), F.col("ids")[0], F.col("ids")[1])
    reader = spark.read.schema(EDGES)
    return require_edge_schema(reader.option("header", True).csv(path) if fmt == "csv" else reader.format(fmt).load(path))


def write_edges(edges: DataFrame, path: str, fmt: str = "parquet") -> None:
    writer = edges.write.mode("overwrite")
    if fmt == "text":
        edges.select(F.concat_ws("\t", "src", "dst").alias("value")).write.mode("overwrite").text(path)
    else:
        writer.option("header", True).format(fmt).save(path)


def require_edge_schema(edges: DataFrame) -> DataFrame:
    found = dict(edges.dtypes)
    if found.get("src") != "bigint" or found.get("dst") != "bigint":
        raise ValueError(f"edges need src and dst as bigint, not {found}")
    return edges.select("src", "dst")
