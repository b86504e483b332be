"""Registered queries against DuckDB on the smallest tables."""

import duckdb
import pytest

import __spark_entry__ as entry
from levelgrid import catalog

DATA = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SAMPLE = [
    "edges_web", "edges_dup", "rmat_tuples_s8", "relabel_degree_ps", "grid_cells_op_2x2", "csc_columns_ps", "edge_map_units", "bfs_op_levels", "chain_levels", "bfs_grid_history", "bfs_grid_kernel",
    "pred_owner_first", "traffic_fold_history", "traffic_expand", "codec_bytes_auto", "wasted_fold", "traffic_1d_vs_2d", "validate_corrupt", "components_dup", "diameter_bounds_geo", "max_flow_nation",
    "stream_session", "stream_incremental_levels", "io_text_edge_list", "join_range_cumul", "udtf_edge_work", "udtf_unpack_bits", "fn_cosine_pairs",
]


@pytest.fixture(scope="module")
def database():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{DATA}/{t}.parquet')")
    return c


def comparable(frame):
    frame = frame[sorted(frame.columns)].astype(object).where(frame.notna(), None)
    return sorted((tuple(round(x, 6) if isinstance(x, float) else str(x) if hasattr(x, "year") else x for x in r) for r in frame.itertuples(index=False)), key=str)


@pytest.mark.parametrize("name", SAMPLE)
def test_query_against_sql(spark, database, name):
    ours = catalog.QUERIES[name](spark, DATA).toPandas()
    theirs = database.execute(catalog.ORACLE_SQL[name]).df()
    assert sorted(ours.columns) == sorted(theirs.columns)
    assert comparable(ours) == comparable(theirs)


def test_contract(spark):
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert set(catalog.QUERIES) <= set(entry.queries())
    assert entry.entry(spark).count() > 0


def test_sent_bytes_against_sql_in_blocks_of_many_buckets(spark, tmp_path):
    """Blocks of 46,875 places are two buckets; bitmaps with one and with both of them set, and lists, as the SQL has them."""
    lines = [*((o, 0) for o in range(2_000)), (0, 1), *((o, 1) for o in range(78_700, 80_700)), *((o, 1) for o in (100_000, 135_000))]
    c = duckdb.connect()
    for name, rows in (
        ("orders", "SELECT range AS o_orderkey FROM range(700000)"),
        ("part", "SELECT range AS p_partkey FROM range(50000)"),
        ("lineitem", f"SELECT * FROM (VALUES {', '.join(map(str, lines))}) x(l_orderkey, l_partkey)"),
    ):
        c.execute(f"COPY ({rows}) TO '{tmp_path}/{name}.parquet'")
        c.execute(f"CREATE VIEW {name} AS SELECT * FROM read_parquet('{tmp_path}/{name}.parquet')")
    ours = catalog.QUERIES["codec_bytes_auto"](spark, str(tmp_path)).toPandas()
    theirs = c.execute(catalog.ORACLE_SQL["codec_bytes_auto"]).df()
    assert set(theirs["kind"]) == {"list", "bitmap"}
    assert sorted(ours.columns) == sorted(theirs.columns)
    assert comparable(ours) == comparable(theirs)
