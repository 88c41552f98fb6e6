"""Builders against the hand-worked example and edge cases."""

import pytest
from pyspark.sql import functions as F

from graphslices import cost, edges as E, layout as L
from graphslices.schema import MARK

EXAMPLE = [(1, 2), (1, 3), (2, 4), (3, 4), (4, 5)]


def graph(spark, pairs):
    return E.normalize_edges(spark.createDataFrame(pairs, "src long, dst long"))


def ids(spark, values):
    return spark.createDataFrame([(v,) for v in values], "id long")


def test_worked_example(spark):
    lay = L.build_pattern_slices(graph(spark, EXAMPLE), 2, None, vertices=ids(spark, [6]))
    got = {r.chunk_id: (r.width, r.col) for r in lay.slices.collect()}
    assert got == {0: (3, [2, 2, 3, 3, 4, MARK]), 1: (2, [0, 0, 1, 1]), 2: (1, [0, MARK])}
    assert [r.id for r in lay.positions.orderBy("pos").collect()] == [4, 1, 2, 3, 5, 6]
    assert cost.cells_exact(6, 10, 2, 2) == {"al": 16, "csr": 26, "valued": 30, "pattern": 18}
    assert cost.cells_formula(6, 10, 2, 2)["valued"] == 28
    assert cost.storage_cells(lay).first().cells_measured == 18
    assert {r.chunk_id: (r.cl, r.cs) for r in L.chunk_directory(lay).collect()} == {0: (3, 0), 1: (2, 6), 2: (1, 10)}
    assert sorted(L.chunk_row(lay, 0).where("chunk_id = 0").first().col) == [2, 3, 4]


def test_tiles_keep_slots_and_split_wide_chunks(spark):
    lay = L.build_pattern_slices(graph(spark, EXAMPLE), 2, None, vertices=ids(spark, [6]))
    tiled = L.tile_slices(lay, 2)
    assert sorted((r.chunk_id, r.tile_id, r.width) for r in tiled.slices.collect()) == [(0, 0, 2), (0, 1, 1), (1, 0, 2), (2, 0, 1)]
    assert cost.product_slots(tiled).first()[0] == cost.product_slots(lay).first()[0] == 12
    direct = L.build_pattern_slices(graph(spark, EXAMPLE), 2, None, tile_width=2, vertices=ids(spark, [6]))
    key = lambda x: sorted((r.chunk_id, r.tile_id, r.width, tuple(r.col)) for r in x.slices.collect())
    assert key(direct) == key(tiled)


CASES = {
    "one edge": [(0, 1)], "path": [(i, i + 1) for i in range(5)], "star": [(0, i) for i in range(1, 10)], "clique": [(i, j) for i in range(6) for j in range(i)],
    "loops and repeats": [(1, 1), (1, 2), (2, 1), (1, 2)], "large ids": [(2**40, 2**41), (2**41, 5)], "two parts": [(0, 1), (7, 8), (8, 9)], "row lengths": [(i, 100 + j) for i in range(1, 10) for j in range(i)],
}


@pytest.mark.parametrize("name", CASES)
@pytest.mark.parametrize("c,sigma", [(2, 1), (8, 8), (4, None)])
def test_round_trip(spark, name, c, sigma):
    e = graph(spark, CASES[name])
    want = {(r.src, r.dst) for r in e.collect()}
    for lay in (L.build_pattern_slices(e, c, sigma, tile_width=3), L.build_valued_slices(e, c, sigma)):
        assert {(r.src, r.dst) for r in L.slices_to_edges(lay).collect()} == want
        assert lay.slices.where(F.size("col") != F.col("width") * c).count() == 0


def test_stretches_of_columns_give_the_same_slots(spark):
    e = graph(spark, CASES["clique"] + [(0, 50 + i) for i in range(20)])
    key = lambda x: sorted((r.chunk_id, r.tile_id, tuple(r.col)) for r in x.slices.collect())
    assert key(L.build_slices(e, 4, None)) == key(L.build_slices(e, 4, None, spread=4))


def test_empty_and_isolated(spark):
    e = graph(spark, [])
    lay = L.build_pattern_slices(e, 4, None, vertices=ids(spark, [3, 9]))
    assert [(r.chunk_id, r.width, r.col) for r in lay.slices.collect()] == [(0, 0, [])]
    assert L.slices_to_edges(lay).count() == 0


def test_values_are_kept(spark):
    w = spark.createDataFrame([(1, 2, 5.0), (2, 1, 5.0), (2, 3, 2.5), (3, 2, 2.5)], "src long, dst long, w double")
    lay = L.build_valued_slices(w, 2, None, "w")
    assert {(r.src, r.dst, r.val) for r in L.slices_to_edges(lay).collect()} == {(1, 2, 5.0), (2, 1, 5.0), (2, 3, 2.5), (3, 2, 2.5)}


def test_csr_offsets_and_save(spark, tmp_path):
    e = graph(spark, CASES["star"])
    rows = L.build_csr(e).orderBy("vertex").collect()
    assert [r.offset for r in rows] == [0, *range(9, 18)]
    lay = L.build_pattern_slices(e, 4, None)
    L.save_layout(lay, str(tmp_path / "l"))
    again = L.open_layout(spark, str(tmp_path / "l"))
    assert (again.c, again.n, again.nnz) == (4, 10, 18)
    assert again.slices.count() == lay.slices.count()
    assert cost.layout_bytes(spark, str(tmp_path / "l")).agg(F.sum("bytes")).first()[0] > 0


def test_small_scopes_do_not_change_padding(spark):
    e = graph(spark, CASES["row lengths"])
    pad = {r.sigma: r.pad_slots for r in cost.padding_by_sigma(E.degrees(e), 8, [1, 8, None]).collect()}
    assert pad[1] == pad[8] >= pad[0]
    top = E.degree_summary(E.degrees(e))
    assert pad[0] <= cost.padding_bound(top, 8).first().bound


def test_ladder_and_widths():
    assert L.sigma_ladder(1000, 8) == [1, 8, 32, 128, 512, 1000]
    assert [L.lane_width(x) for x in ("avx32", "knl32", "gpu")] == [8, 16, 32]
