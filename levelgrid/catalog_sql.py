"""SQL for DuckDB that tells what the registered graph queries return."""

from __future__ import annotations

from levelgrid.sources.graphs import PRIME, SEED_STEP, SHIFT, SPREAD, STEP

_CUSTOMER_LINES = "lineitem JOIN orders ON l_orderkey = o_orderkey"

#: input tuples (src, dst) of each graph
EDGES = {
    "op": "SELECT l_orderkey AS src, l_partkey + (SELECT count(*) FROM orders) AS dst FROM lineitem",
    "ps": "SELECT l_partkey AS src, l_suppkey + (SELECT count(*) FROM part) AS dst FROM lineitem",
    "cp": f"SELECT o_custkey AS src, l_partkey + (SELECT count(*) FROM customer) AS dst FROM {_CUSTOMER_LINES}",
    "cs": f"SELECT o_custkey AS src, l_suppkey + (SELECT count(*) FROM customer) AS dst FROM {_CUSTOMER_LINES}",
    "uk": "SELECT user_id AS src, CAST(props->>'$.k' AS BIGINT) + (SELECT max(user_id) + 1 FROM events) AS dst FROM events",
    "geo": """SELECT n_regionkey::BIGINT AS src, (n_nationkey + (SELECT count(*) FROM region))::BIGINT AS dst FROM nation
              UNION ALL SELECT c_nationkey + (SELECT count(*) FROM region), c_custkey + (SELECT count(*) FROM region) + (SELECT count(*) FROM nation) FROM customer
              UNION ALL SELECT s_nationkey + (SELECT count(*) FROM region), s_suppkey + (SELECT count(*) FROM region) + (SELECT count(*) FROM nation) + (SELECT count(*) FROM customer) FROM supplier""",
    "cc": """SELECT a.conv_id * w + a.turn AS src, a.conv_id * w + a.turn + 1 AS dst
             FROM (SELECT DISTINCT conv_id, turn FROM conversations) a JOIN (SELECT DISTINCT conv_id, turn FROM conversations) b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1,
                  (SELECT max(turn) + 1 AS w FROM conversations)""",
    "web": """SELECT page_id AS src, nth + (SELECT count(*) FROM pages) AS dst
              FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS target FROM pages) f
              JOIN (SELECT target, row_number() OVER (ORDER BY target) - 1 AS nth
                    FROM (SELECT DISTINCT unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS target FROM pages)) n USING (target)""",
    "dup": """SELECT doc_id AS src, nth + (SELECT count(*) FROM documents) AS dst
              FROM (SELECT DISTINCT doc_id, line FROM (SELECT doc_id, lower(trim(unnest(string_split(text, chr(10))), ' ')) AS line FROM documents) WHERE length(line) >= 20) l
              JOIN (SELECT line, row_number() OVER (ORDER BY line) - 1 AS nth FROM (
                      SELECT line FROM (SELECT DISTINCT doc_id, line FROM (SELECT doc_id, lower(trim(unnest(string_split(text, chr(10))), ' ')) AS line FROM documents) WHERE length(line) >= 20)
                      GROUP BY line HAVING count(*) > 1)) n USING (line)""",
    "knn": "SELECT vec_id AS src, label + (SELECT count(*) FROM embeddings) AS dst FROM embeddings",
}
_AT = {}
_sum = "0"
for _t in ("region", "nation", "customer", "supplier", "part", "orders"):
    _AT[_t] = _sum
    _sum += f" + (SELECT count(*) FROM {_t})"
EDGES["all"] = f"""SELECT n_nationkey + {_AT["nation"]} AS src, n_regionkey::BIGINT AS dst FROM nation
  UNION ALL SELECT c_custkey + {_AT["customer"]}, c_nationkey + {_AT["nation"]} FROM customer
  UNION ALL SELECT s_suppkey + {_AT["supplier"]}, s_nationkey + {_AT["nation"]} FROM supplier
  UNION ALL SELECT o_orderkey + {_AT["orders"]}, o_custkey + {_AT["customer"]} FROM orders
  UNION ALL SELECT l_orderkey + {_AT["orders"]}, l_partkey + {_AT["part"]} FROM lineitem
  UNION ALL SELECT l_partkey + {_AT["part"]}, l_suppkey + {_AT["supplier"]} FROM lineitem"""


def rmat(scale: int, edge_factor: int = 16, seed: int = 42) -> str:
    cuts = (1224065679, 1632087572, 2040109465)
    state = lambda k: f"(x * {pow(STEP, k, PRIME)} % {PRIME})"
    src = " + ".join(f"(CASE WHEN {state(k)} >= {cuts[1]} THEN {1 << (scale - 1 - k)} ELSE 0 END)" for k in range(scale))
    dst = " + ".join(f"(CASE WHEN ({state(k)} >= {cuts[0]} AND {state(k)} < {cuts[1]}) OR {state(k)} >= {cuts[2]} THEN {1 << (scale - 1 - k)} ELSE 0 END)" for k in range(scale))
    first = f"((id * {SPREAD} + {seed * SEED_STEP + SHIFT}) % {PRIME - 1} + 1) * {STEP * SPREAD % PRIME} % {PRIME}"
    return f"SELECT ({src})::BIGINT AS src, ({dst})::BIGINT AS dst FROM (SELECT {first} AS x FROM (SELECT unnest(range({edge_factor << scale})) AS id))"


def tuples(gid: str) -> str:
    return rmat(int(gid[4:])) if gid.startswith("rmat") else EDGES[gid]


def simple(gid: str) -> str:
    """t: input tuples; e: the undirected graph."""
    return f"t AS ({tuples(gid)}), e AS (SELECT DISTINCT src, dst FROM (SELECT src, dst FROM t UNION ALL SELECT dst, src FROM t) WHERE src <> dst)"


def walked(root: str = "0", cap: int = 12) -> str:
    """levels (v, level) from e."""
    return f"""walk(v, level) AS (SELECT ({root})::BIGINT, 0 UNION SELECT e.dst, level + 1 FROM walk JOIN e ON e.src = walk.v WHERE level < {cap}),
      levels AS (SELECT v, min(level) AS level FROM walk GROUP BY v)"""


def with_levels(gid: str, rest: str, root: str = "0", cap: int = 12) -> str:
    return f"WITH RECURSIVE {simple(gid)}, {walked(root, cap)} {rest}"


def with_affine(gid: str, n: str, rest: str, root: str, cap: int = 12) -> str:
    """Like with_levels, ids relabelled by v -> (7919 v + 13) mod n."""
    t = f"SELECT (src * 7919 + 13) % {n} AS src, (dst * 7919 + 13) % {n} AS dst FROM ({tuples(gid)})"
    e = "SELECT DISTINCT src, dst FROM (SELECT src, dst FROM t UNION ALL SELECT dst, src FROM t) WHERE src <> dst"
    return f"WITH RECURSIVE t AS ({t}), e AS ({e}), {walked(root, cap)} {rest}"


def grid_edges(nb: str, r: int, c: int) -> str:
    """c: edges with grid row, grid column, the target's owner column, and the source's level."""
    return f"""c AS (SELECT e.src, e.dst, ((e.dst // {nb}) % {r})::INT AS gi, (e.src // ({nb} * {r}))::INT AS gj, (e.dst // ({nb} * {r}))::INT AS gt, l.level AS lv
      FROM e JOIN levels l ON l.v = e.src)"""


def fold(dedup: str, c: int) -> str:
    """(level, sender, receiver, vertices) in closed form from c."""
    inner = {
        "history": "SELECT gi, gj, gt, dst, 1 + min(lv) AS level FROM c WHERE gj <> gt GROUP BY gi, gj, gt, dst",
        "level": "SELECT DISTINCT gi, gj, gt, dst, 1 + lv AS level FROM c WHERE gj <> gt",
        "receiver": "SELECT gi, gj, gt, dst, 1 + lv AS level FROM c WHERE gj <> gt",
    }[dedup]
    return f"SELECT level, (gi * {c} + gj)::INT AS sender, (gi * {c} + gt)::INT AS receiver, count(*) AS vertices FROM ({inner}) GROUP BY 1, 2, 3"


def expand(nb: str, r: int, c: int) -> str:
    return f"""SELECT level + 1 AS level, (gi * {c} + gj)::INT AS sender, (i * {c} + gj)::INT AS receiver, count(*) AS vertices
      FROM (SELECT level, ((v // {nb}) % {r})::INT AS gi, (v // ({nb} * {r}))::INT AS gj FROM levels), (SELECT unnest(range({r})) AS i) WHERE i <> gi GROUP BY 1, 2, 3"""


def modulo_fold(dedup: str, p: int) -> str:
    inner = {
        "history": f"SELECT src % {p} AS s, dst % {p} AS d, dst, 1 + min(level) AS level FROM e JOIN levels ON v = src WHERE src % {p} <> dst % {p} GROUP BY 1, 2, 3",
        "level": f"SELECT DISTINCT src % {p} AS s, dst % {p} AS d, dst, 1 + level AS level FROM e JOIN levels ON v = src WHERE src % {p} <> dst % {p}",
        "receiver": f"SELECT src % {p} AS s, dst % {p} AS d, dst, 1 + level AS level FROM e JOIN levels ON v = src WHERE src % {p} <> dst % {p}",
    }[dedup]
    return f"SELECT level, s::INT AS sender, d::INT AS receiver, count(*) AS vertices FROM ({inner}) GROUP BY 1, 2, 3"


def sizes(messages: str, nb: str) -> str:
    return f"""SELECT level, sender, receiver, vertices, vertices * 4 AS bytes_list, (({nb} + 7) // 8)::BIGINT AS bytes_bitmap,
      CASE WHEN vertices > {nb} // 32 THEN ({nb} + 7) // 8 ELSE vertices * 4 END::BIGINT AS bytes_auto,
      CASE WHEN vertices > {nb} // 32 THEN 'bitmap' ELSE 'list' END AS kind FROM ({messages})"""
