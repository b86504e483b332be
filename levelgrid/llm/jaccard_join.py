"""Similarity join of documents on word 5-grams, Jaccard 0.8 or more, by chosen paths.

Documents with equal 5-gram sets are one text.  For the other pairs the search space is split along
chosen paths: a text is put in a bucket for each of some sampled tokens (coordinates of its MinHash
signature, so that two texts share a token as often as their sets agree); a bucket of at most LIMIT
texts is searched by brute force over signatures, a larger one is split again on further sampled
tokens, seeded by its path.  RUNS independent tokens at the root repeat the search: a pair at
the threshold misses all of them once in five to that power, 10**-7.

In a large bucket of near copies, splitting parts nothing.  There a few pivots are compared with all
others first: texts very near a pivot leave, since whatever is similar to them is linked to the pivot
as well (triangle inequality, a lower bound for links to pivots).  A bucket that is still large after
DEPTH splits becomes a group as it is: the exact step below takes groups of any size.

What the search finds are not pairs but groups, stars joined into components, so a group of n texts
costs n rows.  The exact step then computes each pair's Jaccard coefficient inside the groups: a
group is dealt in blocks of texts, and pairs of blocks meet in tasks of bounded memory, which
return for each text the number of its links, and stars again.

Scale: signatures are 256 bytes a text; 5-gram sets are made only for texts in groups.  Work on a
group of n distinct near copies is quadratic in n by the nature of exact link counts, in pieces of
BLOCK x BLOCK, and its rows are n * n / BLOCK.

Edge cases: a text of 1 to 4 words has one gram, all its words; a null or wordless text has none, links to
nothing and is a class of its own; a null doc_id takes part, is named by no class unless all of its
class have none; one doc_id may name several texts, each of which is judged by itself; repeated rows are
copies of each other; an empty table gives no rows; `near_duplicates` ignores other columns, `one_of_each`
keeps them whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelgrid.operators.components import star_components
from levelgrid.plans.state import held

from .common import settled
from .textkit import U64, Words, grams, slices, split_words, text_buffer, text_column

GRAM, COORDINATES = 5, 64
RUNS, CHILDREN, DEPTH = 10, 2, 12
LIMIT, PIVOTS = 2000, 4
#: texts, and 5-grams, of a block in the exact step
BLOCK, BLOCK_GRAMS = 512, 1 << 20
#: agreeing coordinates of 64: candidates (a pair at 0.8 falls below once in 10**5), links to pivots, and leaving with a pivot;
#: a text at 0.55 from a pivot leaves, what is similar to it is at 0.35 or nearer and so linked to the pivot too
CANDIDATE, PIVOT_LINK, PIVOT_NEAR = 36, 12, 42

#: rows with a text or a gram set can be large: fewer of them stand in memory at once
SMALL_BATCHES = {"spark.sql.execution.arrow.maxRecordsPerBatch": "500"}

#: with the doc_id, what tells the rows of a table apart
def _text_key():
    return F.xxhash64("text")


_rng = np.random.default_rng(7)
_FACTORS = _rng.integers(1, 2**63, COORDINATES, dtype=np.int64).astype(U64) * U64(2) + U64(1)


def gram_sets(words: Words, n: int = GRAM) -> list[np.ndarray]:
    """The sorted distinct n-gram hashes of each document; of all its words where these are fewer."""
    values, at = grams(words, n)
    edges = np.searchsorted(at, words.first)
    out = []
    for i, (a, b) in enumerate(zip(edges, edges[1:])):
        if b > a:
            out.append(np.unique(values[a:b]))
        elif words.counts[i]:
            own = words.value[words.first[i] : words.first[i + 1]]
            out.append(np.array([xxhash.xxh3_64_intdigest(own.tobytes())], dtype=U64))
        else:
            out.append(np.zeros(0, dtype=U64))
    return out


def set_name(values: np.ndarray) -> int:
    """A set's 64-bit name, signed."""
    return int(np.int64(np.uint64(xxhash.xxh3_64_intdigest(values.tobytes(), seed=5)).astype(np.int64)))


def minhashes(sets: list[np.ndarray]) -> np.ndarray:
    """A row of COORDINATES 32-bit minima for each set; the sets must not be empty."""
    every = np.concatenate(sets)
    starts = np.cumsum([0, *(len(x) for x in sets[:-1])])
    out = np.empty((len(sets), COORDINATES), dtype=np.uint32)
    for c in range(COORDINATES):
        out[:, c] = np.minimum.reduceat(((every * _FACTORS[c]) >> U64(32)).astype(np.uint32), starts)
    return out


def signatures(documents: DataFrame, n: int = GRAM) -> DataFrame:
    """(doc_id, text_key, node, grams, signature) of each row of (doc_id, text): a hash of the text, its gram set's name (null if it has none) and size."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch):
                sets = gram_sets(split_words(*text_buffer(text_column(part))), n)
                full = [i for i, x in enumerate(sets) if len(x)]
                names, signed = [None] * len(sets), [None] * len(sets)
                if full:
                    for i, row in zip(full, minhashes([sets[i] for i in full])):
                        names[i], signed[i] = set_name(sets[i]), row.tobytes()
                columns = [part.column(0).cast(pa.int64()), part.column(2), pa.array(names, pa.int64()), pa.array([len(x) for x in sets], pa.int64()), pa.array(signed, pa.binary())]
                yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "text_key", "node", "grams", "signature"])

    return documents.select("doc_id", "text", _text_key().alias("text_key")).mapInArrow(run, "doc_id long, text_key long, node long, grams long, signature binary")


def _token(coordinate) -> F.Column:
    return F.substring("signature", coordinate * 4 + 1, F.lit(4))


def _shared(rows: DataFrame, most: int) -> DataFrame:
    """`rows` (bucket, node, ...) of buckets with two nodes or more, with their number n."""
    counts = rows.groupBy("bucket").agg(F.count("*").alias("n")).where("n > 1")
    return settled(rows.join(counts, "bucket"), most)


def _groups(linked: np.ndarray) -> np.ndarray:
    """Components of a boolean adjacency matrix: for each row the smallest row it is joined to."""
    n = len(linked)
    label = np.arange(n, dtype=np.int32)
    while True:
        new = label.copy()
        for low in range(0, n, 256):
            part = slice(low, low + 256)
            new[part] = np.minimum(new[part], np.where(linked[part], label[None, :], np.int32(n)).min(axis=1, initial=n))
        new = new[new]
        if (new == label).all():
            return label
        label = new


def _whole_buckets(batches: Iterator[pa.RecordBatch], key: str) -> Iterator[pa.RecordBatch]:
    """Record batches cut where the sorted key changes, so that no bucket is in two of them."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        keys = batch.column(batch.schema.get_field_index(key)).to_numpy(zero_copy_only=False)
        cut = int(np.searchsorted(keys, keys[-1], side="left"))
        if cut or (held and held[0].column(held[0].schema.get_field_index(key))[0].as_py() != keys[0]):
            if cut:
                held.append(batch.slice(0, cut))
            yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
            held = []
        held.append(batch.slice(cut))
    if held:
        yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]


def _sketches(column: pa.Array) -> np.ndarray:
    data = np.frombuffer(b"".join(column.to_pylist()), dtype=np.uint32)
    return data.reshape(-1, COORDINATES)


def brute_force(rows: DataFrame) -> DataFrame:
    """(u, v) stars over candidates, for small buckets (bucket, node, signature)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _whole_buckets(batches, "bucket"):
            buckets = batch.column(0).to_numpy(zero_copy_only=False)
            nodes = batch.column(1).to_numpy(zero_copy_only=False)
            sketches = _sketches(batch.column(2))
            edges = np.flatnonzero(np.concatenate([[True], buckets[1:] != buckets[:-1], [True]]))
            us, vs = [], []
            for a, b in zip(edges, edges[1:]):
                if b - a < 2:
                    continue
                own = sketches[a:b]
                if b - a == 2:
                    if np.count_nonzero(own[0] == own[1]) >= CANDIDATE:
                        us.append(nodes[a : a + 1])
                        vs.append(nodes[b - 1 : b])
                    continue
                agree = np.zeros((b - a, b - a), dtype=np.uint8)
                for c in range(COORDINATES):
                    agree += own[:, c, None] == own[None, :, c]
                root = _groups(agree >= CANDIDATE)
                moved = np.flatnonzero(root != np.arange(b - a))
                us.append(nodes[a:b][moved])
                vs.append(nodes[a:b][root[moved]])
            if us:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(us)), pa.array(np.concatenate(vs))], names=["u", "v"])

    return rows.select("bucket", "node", "signature").repartition("bucket").sortWithinPartitions("bucket").mapInArrow(run, "u long, v long")


def against_pivots(rows: DataFrame) -> DataFrame:
    """For large buckets' rows (bucket, node, signature, pivots): a link to the first pivot that each is near, and whether it leaves.

    Pivots that a row is near at once are linked to each other in rows of their own, which leave.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            own = _sketches(batch.column(2))
            pivots = batch.column(3)
            sizes = np.diff(np.frombuffer(pivots.buffers()[1], dtype=np.int32)[pivots.offset : pivots.offset + len(pivots) + 1])
            flat = pivots.flatten()
            of = np.repeat(np.arange(len(own)), sizes)
            agree = (own[of] == _sketches(flat.field("signature"))).sum(axis=1)
            names = flat.field("node").to_numpy(zero_copy_only=False)
            link: list[int | None] = [None] * len(own)
            joined: set[tuple[int, int]] = set()
            for k in np.flatnonzero(agree >= PIVOT_LINK).tolist():
                first = link[of[k]]
                if first is None:
                    link[of[k]] = int(names[k])
                else:
                    joined.add((int(names[k]), first))
            leaves = np.bincount(of, weights=agree >= PIVOT_NEAR, minlength=len(own)) > 0
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), pa.array(link, pa.int64()), pa.array(leaves)], names=["bucket", "node", "signature", "link", "leaves"])
            if joined:
                more = [pa.array([None] * len(joined), pa.int64()), pa.array([a for a, _ in joined], pa.int64()), pa.array([None] * len(joined), pa.binary()), pa.array([b for _, b in joined], pa.int64()), pa.array([True] * len(joined))]
                yield pa.RecordBatch.from_arrays(more, names=["bucket", "node", "signature", "link", "leaves"])

    return rows.select("bucket", "node", "signature", "pivots").mapInArrow(run, "bucket long, node long, signature binary, link long, leaves boolean")


def candidate_edges(texts: DataFrame, n: int, limit: int = LIMIT, depth: int = DEPTH) -> list[DataFrame]:
    """Stars (u, v) over all n texts (node, signature) whose signatures show a candidate pair.

    Root buckets are counted on ids alone; signatures join only what shares a bucket, and stay with it below.
    """
    signed = texts.select("node", "signature")
    tokens = F.array(*(F.xxhash64(F.lit(run), _token(F.lit(run))) for run in range(RUNS)))
    shared = _shared(signed.select("node", F.explode(tokens).alias("bucket")), n * RUNS)
    found = []
    for level in range(depth + 1):
        signs = (lambda frame: frame.join(signed, "node")) if level == 0 else (lambda frame: frame)
        found.append(settled(brute_force(signs(shared.where(F.col("n") <= limit))), n * RUNS))
        large = shared.where(F.col("n") > limit)
        if large.isEmpty():
            return found
        if level == depth:
            roots = large.groupBy("bucket").agg(F.min("node").alias("v"))
            found.append(large.select("bucket", F.col("node").alias("u")).join(roots, "bucket").select("u", "v"))
            return found
        large = signs(large.drop("n"))
        first = lambda i: F.min(F.struct(F.xxhash64(F.lit(i), "node").alias("h"), "node", "signature")).alias(f"p{i}")
        chosen = large.groupBy("bucket").agg(*(first(i) for i in range(PIVOTS)))
        pivots = chosen.select("bucket", F.array_distinct(F.array(*(F.struct(f"p{i}.node", f"p{i}.signature") for i in range(PIVOTS)))).alias("pivots"))
        told = settled(against_pivots(large.join(pivots, "bucket")), n * RUNS)
        found.append(told.where("link is not null").select(F.col("node").alias("u"), F.col("link").alias("v")))
        coordinate = lambda child: (RUNS + F.pmod(F.xxhash64("bucket", F.lit(child)), F.lit(COORDINATES - RUNS))).cast("int")
        children = F.array(*(F.xxhash64("bucket", F.lit(level), coordinate(j), _token(coordinate(j))) for j in range(CHILDREN)))
        shared = _shared(told.where(~F.col("leaves")).select("node", "signature", F.explode(F.array_distinct(children)).alias("bucket")), n * RUNS)
    return found


def similar(sets: list[np.ndarray], split: int | None = None) -> np.ndarray:
    """Which pairs have a Jaccard coefficient of at least 0.8; with `split`, only those across that place."""
    sizes = np.array([len(x) for x in sets], dtype=np.int64)
    every = np.concatenate(sets)
    owner = np.repeat(np.arange(len(sets)), sizes)
    order = np.argsort(every, kind="stable")
    every, owner = every[order], owner[order]
    new = np.concatenate([[True], every[1:] != every[:-1]])
    column = np.cumsum(new) - 1
    often = np.bincount(column) > 1
    keep = often[column]
    column, owner = (np.cumsum(often) - 1)[column[keep]], owner[keep]
    common = np.zeros((len(sets), len(sets)), dtype=np.float32)
    width = max(256, (4 << 20) // max(1, len(sets)))
    for low in range(0, int(often.sum()), width):
        a, b = np.searchsorted(column, [low, low + width])
        held = np.zeros((len(sets), width), dtype=np.float32)
        held[owner[a:b], column[a:b] - low] = 1
        common += held @ held.T
    common = np.rint(common).astype(np.int64)
    out = 5 * common >= 4 * (sizes[:, None] + sizes[None, :] - common)
    np.fill_diagonal(out, False)
    if split is not None:
        out[:split, :split] = False
        out[split:, split:] = False
    return out


def with_sets(documents: DataFrame, members: DataFrame) -> DataFrame:
    """`members` (node, doc, ...) with the sorted gram set of each, from the text of the document `doc` (doc_id, text_key)."""
    own = documents.select(F.col("doc_id").cast("long").alias("of"), _text_key().alias("of_key"), "text")
    told = own.join(members, F.col("of").eqNullSafe(F.col("doc.doc_id")) & (F.col("of_key") == F.col("doc.text_key"))).drop("of", "of_key", "doc")
    names = [c for c in told.columns if c != "text"]
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in told.schema if f.name != "text"), "grams binary"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch):
                sets = gram_sets(split_words(*text_buffer(text_column(part))))
                nodes = part.column(part.schema.get_field_index("node")).to_pylist()
                right = [set_name(x) == y for x, y in zip(sets, nodes)]
                columns = [part.column(part.schema.get_field_index(c)) for c in names]
                yield pa.RecordBatch.from_arrays([*columns, pa.array([x.tobytes() for x in sets], pa.binary())], names=[*names, "grams"]).filter(pa.array(right))

    return told.select("text", *names).mapInArrow(run, schema)


def exact_links(members: DataFrame) -> DataFrame:
    """(node, root, texts, documents, dealt) for members (key, node, side, copies, grams) of block pairs.

    A key is one block (side 0), or two of them (sides 1 and 2), of which only links across are told.

    One row for each text and pair of blocks: how many texts and documents it is linked to there, and the
    smallest node it is joined to.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _whole_buckets(batches, "key"):
            keys = batch.column(0).to_numpy(zero_copy_only=False)
            edges = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1], [True]]))
            for a, b in zip(edges, edges[1:]):
                part = batch.slice(a, b - a)
                nodes, sides, copies = (part.column(i).to_numpy(zero_copy_only=False) for i in (1, 2, 3))
                order = np.lexsort((nodes, sides))
                order = order[np.concatenate([[True], (nodes[order][1:] != nodes[order][:-1]) | (sides[order][1:] != sides[order][:-1])])]
                nodes, sides, copies = nodes[order], sides[order], copies[order]
                raw = part.column(4)
                sets = [np.frombuffer(raw[int(i)].as_py(), dtype=U64) for i in order]
                linked = similar(sets, int(np.searchsorted(sides, 2)) if sides[0] else None)
                # the smallest node of each group stands for it
                by_node = np.argsort(nodes, kind="stable")
                root = np.empty(len(nodes), dtype=np.int64)
                root[by_node] = nodes[by_node][_groups(linked[np.ix_(by_node, by_node)])]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(nodes), pa.array(root), pa.array(linked.sum(axis=1).astype(np.int64)), pa.array((linked @ copies).astype(np.int64))], names=["node", "root", "texts", "documents"]
                )

    rows = members.select("key", "node", "side", "copies", "grams").repartition("key").sortWithinPartitions("key")
    return rows.mapInArrow(run, "node long, root long, texts long, documents long")


def classified(documents: DataFrame) -> DataFrame:
    """(doc_id, text_key, node, first, n_links, n_texts) of each row: `first` is the document (doc_id, text_key) that stands for its class.

    That is the one with the smallest doc_id, and of texts with that doc_id the one with the smallest key;
    a row without grams has no node and no first.
    """
    with held(documents.sparkSession, SMALL_BATCHES):
        signed = settled(signatures(documents))
    n = signed.count()
    # documents without a doc_id come last
    least = F.min(F.struct(F.col("doc_id").isNull().alias("unnamed"), "doc_id", "text_key")).alias("doc")
    texts = settled(signed.where("node is not null").groupBy("node").agg(least, F.count("*").alias("copies"), F.first("grams").alias("grams"), F.first("signature").alias("signature")), n)
    edges = None
    with held(documents.sparkSession, {"spark.sql.execution.arrow.maxRecordsPerBatch": "4000"}):
        for found in candidate_edges(texts, n):
            edges = found if edges is None else edges.unionAll(found)
    groups = star_components(edges, rows=n * RUNS).select(F.col("v").alias("node"), F.col("component").alias("part"))
    groups = groups.join(texts.drop("signature"), "node")
    blocks = F.greatest(F.ceil(F.count("*") / BLOCK), F.ceil(F.sum("grams") / BLOCK_GRAMS)).cast("int")
    sizes = groups.groupBy("part").agg(blocks.alias("blocks"))
    members = settled(groups.join(sizes, "part").withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int")), n)
    sets = with_sets(documents, members.select("node", "doc", "copies", "part", "blocks", "block"))
    # each block meets itself and every other one: (first, second) with first <= second
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    pairs = sets.withColumn("other", other).withColumn("first", F.least("block", "other")).withColumn("second", F.greatest("block", "other"))
    side = F.when(F.col("first") == F.col("second"), 0).when(F.col("block") == F.col("first"), 1).otherwise(2)
    pairs = pairs.withColumn("side", side).withColumn("key", F.xxhash64("part", "first", "second"))
    with held(documents.sparkSession, SMALL_BATCHES):
        links = settled(exact_links(pairs), n * RUNS)
    counts = links.groupBy("node").agg(F.sum("texts").alias("texts"), F.sum("documents").alias("documents"), F.min("root").alias("root"))
    joined = star_components(links.select(F.col("node").alias("u"), F.col("root").alias("v")), rows=n * RUNS)
    classes = counts.join(joined.select(F.col("v").alias("node"), "component"), "node", "left").select("node", "texts", "documents", F.coalesce("component", "node").alias("component"))
    firsts = classes.join(texts.select("node", "doc"), "node").groupBy("component").agg(F.min("doc").alias("first"))
    told = texts.select("node", "doc", "copies").join(classes.join(firsts, "component"), "node", "left")
    told = told.select(
        F.col("node").alias("of"),
        F.coalesce("first", "doc").alias("first"),
        (F.col("copies") - 1 + F.coalesce("documents", F.lit(0))).alias("n_links"),
        F.coalesce("texts", F.lit(0)).alias("n_texts"),
    )
    return signed.select("doc_id", "text_key", "node").join(told, F.col("node") == F.col("of"), "left").drop("of")


def near_duplicates(documents: DataFrame) -> DataFrame:
    """doc_id, class_id, n_links, n_texts for each row of (doc_id, text).

    class_id is the smallest doc_id among all documents that links join, directly or through others;
    n_links counts the other documents with Jaccard 0.8 or more, copies included; n_texts the different texts among them.
    """
    return classified(documents).select(
        "doc_id",
        F.when(F.col("node").isNull(), F.col("doc_id")).otherwise(F.col("first.doc_id")).alias("class_id"),
        F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"),
        F.coalesce("n_texts", F.lit(0)).cast("long").alias("n_texts"),
    )


def one_of_each(documents: DataFrame) -> DataFrame:
    """The document that stands for each class, with all its columns, and every text that has no words.

    Rows are told apart by doc_id and text: of different texts with one doc_id each is kept or not by its own
    class.  Rows equal in both are one; the smallest of them, by all columns, is kept.
    """
    stands = F.col("node").isNull() | (F.struct("doc_id", "text_key").eqNullSafe(F.struct("first.doc_id", "first.text_key")))
    named = classified(documents).where(stands).groupBy("doc_id", "text_key").agg(F.count("*").alias("n"))
    named = settled(named.select(F.col("doc_id").alias("kept"), F.col("text_key").alias("kept_key"), "n"))
    rows = documents.select(F.col("doc_id").cast("long").alias("of"), _text_key().alias("of_key"), F.struct("*").alias("row"))
    wanted = lambda keep: rows.join(keep, F.col("of").eqNullSafe(F.col("kept")) & (F.col("of_key") == F.col("kept_key")), "left_semi")
    # only rows that are there more than once meet, after partial sums in each task: many of them are no hot key
    more = wanted(named.where("n > 1")).groupBy("of", "of_key").agg(F.min("row").alias("row"))
    return wanted(named.where("n = 1")).select("row.*").unionAll(more.select("row.*"))
