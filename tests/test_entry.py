"""Queries against the oracle on the smallest tables, and generated graphs."""

import glob
import os

import duckdb
import pytest

import __spark_entry__ as entry

SMALL = "/root/testdata/sf0.001"
CHECKED = [
    "bfs_tiles_tropical_supplier_part", "bfs_grid_selmax_supplier_part", "levels_geo_tree", "storage_cells_supplier_part_8", "work_per_iteration_skip_supplier_part_n", "mv_weighted", "kron_edges",
    "edges_as_of", "level_cube", "stream_enrich", "stream_distance", "unpack_chunk", "packed_bit_frontier",
]


def plain(v):
    return round(v, 6) if isinstance(v, float) else v


@pytest.mark.skipif(not os.path.isdir(SMALL), reason="needs the test tables")
@pytest.mark.parametrize("name", CHECKED)
def test_query_equals_oracle(spark, name):
    con = duckdb.connect()
    for f in glob.glob(f"{SMALL}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    df = entry.queries()[name](spark, SMALL)
    want = con.sql(entry.oracle_sql()[name])
    order = [want.columns.index(c) for c in df.columns]
    assert sorted(df.columns) == sorted(want.columns)
    assert sorted(repr([plain(v) for v in r]) for r in df.collect()) == sorted(repr([plain(r[i]) for i in order]) for r in want.fetchall())


@pytest.mark.skipif(not os.path.isdir(SMALL), reason="needs the test tables")
def test_entry(spark):
    assert entry.entry(spark).count() > 0


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_generators(spark):
    from pyspark.sql import functions as F

    from graphslices import generate

    assert generate.er_edges_pairs(spark).count() == 2 * 16193
    k = generate.kronecker_edges(spark)
    assert k.count() == 2 * 18894
    assert generate.er_edges_sampled(spark, 100, 500).where(F.col("src") == F.col("dst")).count() == 0
    with pytest.raises(ValueError):
        generate.er_edges_pairs(spark, 1 << 20)
