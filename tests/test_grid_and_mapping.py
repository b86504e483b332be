"""Grid arithmetic by brute force, the work mapping, and message encodings."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from levelgrid.functions.grid import GridSpec
from levelgrid.operators import codec, kernel, measures


@pytest.mark.parametrize("n,r,c", [(8, 2, 2), (7, 2, 2), (30, 2, 3), (17, 1, 4), (5, 4, 4)])
def test_grid_maps(spark, n, r, c):
    grid = GridSpec(n, r, c)
    v = F.col("id")
    told = spark.range(n).select(
        "id", grid.owner_row(v).alias("i"), grid.owner_column(v).alias("j"), grid.local_row(v).alias("lrow"), grid.local_column(v).alias("lcol"),
        grid.row_to_column(grid.owner_row(v), grid.local_row(v)).alias("back"), grid.global_row(grid.owner_row(v), grid.local_row(v)).alias("v1"), grid.global_column(grid.owner_column(v), grid.local_column(v)).alias("v2"),
    ).collect()
    for x in told:
        b = x["id"] // grid.nb
        assert (x["i"], x["j"]) == (b % r, b // r)
        assert x["v1"] == x["v2"] == x["id"] and x["back"] == x["lcol"]
        assert 0 <= x["lrow"] < grid.rows and 0 <= x["lcol"] < grid.columns
    assert len({(x["i"], x["lrow"]) for x in told}) == n


def test_grid_bounds():
    with pytest.raises(ValueError):
        GridSpec(0, 1, 1)
    with pytest.raises(ValueError):
        GridSpec(1 << 40, 2, 2)
    assert GridSpec(1 << 33, 64, 64).nb == 1 << 21


def by_loop(degrees):
    return [(k, j) for k, d in enumerate(degrees) for j in range(d)]


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 9), max_size=12), st.sampled_from([1, 2, 4, 8]))
def test_work_mapping(degrees, group):
    k, j = kernel.map_units(np.array(degrees, dtype=np.int64), group)
    assert list(zip(k.tolist(), j.tolist())) == by_loop(degrees)


def test_work_mapping_of_23_edges(spark):
    degrees = [4, 0, 5, 1, 0, 6, 7]
    frontier = spark.createDataFrame(list(enumerate(degrees)), "k long, degree long")
    for group in (1, 2, 4, 8):
        told = sorted(tuple(r) for r in kernel.edge_work_map(frontier, group).select("i", "k", "j", "unit").collect())
        assert [(k, j) for _, k, j, _ in told] == by_loop(degrees)
        assert [u for *_, u in told] == [i // group for i in range(23)]


@pytest.mark.parametrize("name", ["list", "bitmap", "auto"])
def test_codec_round_trip(spark, name):
    wanted = [(0, i) for i in (0, 1)] + [(1, i) for i in range(64)] + [(2, 63)] + [(3, i) for i in (32767, 32768, 65535)]
    nb = 70_000
    packed = codec.messages(spark.createDataFrame(wanted, "m long, i long"), ["m"], "i", nb, name)
    assert sorted(tuple(r) for r in codec.unpack(packed, ["m"], "i").collect()) == sorted(wanted)
    assert codec.unpack(packed.where("m > 9"), ["m"], "i").count() == 0


def test_switch(spark):
    assert (codec.bitmap_bytes(1 << 21), codec.switch_threshold(1 << 21)) == (262_144, 65_536)
    told = codec.sized(spark.createDataFrame([(n,) for n in (0, 1, 2, 3, 64)], "vertices long"), 64)
    for r in told.collect():
        assert r["bytes_auto"] == min(4 * r["vertices"], 8) and r["kind"] == ("bitmap" if r["vertices"] > 2 else "list")


def test_model_measures():
    assert measures.partner_counts(GridSpec(1 << 33, 64, 64)) == {"expand": 63, "fold": 63, "two_dimensional": 126, "one_dimensional": 4095}
    assert measures.teps(10, 2.0) == 5.0
    assert measures.shares({"expand": 1.0, "expansion": 5.0, "fold": 2.0, "update": 2.0}) == {"transfer": 0.3, "update": 0.2}
