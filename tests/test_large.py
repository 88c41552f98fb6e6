"""What large graphs need: their source is read once, layouts by arrays equal layouts by joins, levels send back what is new, laws close to 1 / degree do not fail."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from graphslices import catalog, cost, edges as E, experiments, layout as L, product
from graphslices.bfs import bfs_dense
from graphslices.semiring import SEMIRINGS
from test_layout import graph

PATH = [(i, i + 1) for i in range(63)]


def slices(lay):
    return sorted((r.chunk_id, r.tile_id, r.width, *map(tuple, r[3:])) for r in lay.slices.collect())


def test_a_graph_is_drawn_once_for_all_its_layouts(spark):
    seen = spark.sparkContext.accumulator(0)

    def count(batches):
        for b in batches:
            seen.add(len(b))
            yield b

    e = graph(spark, PATH)
    g = experiments.Graph(spark, "", "path", e.mapInArrow(count, e.schema))
    assert g.layout(8, 1).nnz == g.layout(8, None).nnz == seen.value == 2 * len(PATH)


@pytest.mark.parametrize("pairs", [PATH, [(0, k) for k in range(1, 40)] + [(k, k + 1) for k in range(5, 30)], [(i * 10**12, (i * i + 1) * 10**12 + 1) for i in range(30)]])
def test_layouts_by_arrays_equal_layouts_by_joins(spark, pairs):
    e = E.normalize_edges(spark.createDataFrame(pairs, "a long, b long"), "a", "b")
    for c, sigma, tile, valued in ((4, None, 3, True), (8, 4, 4096, False)):
        assert slices(L.build_slices(e, c, sigma, valued=valued, tile_width=tile)) == slices(L.build_slices(e, c, sigma, valued=valued, tile_width=tile, spread=1))


def test_isolated_vertices_keep_their_chunks(spark):
    e, extra = graph(spark, [(0, 1)]), spark.range(40)
    lay = L.build_slices(e, 8, None, vertices=extra)
    assert slices(lay) == slices(L.build_slices(e, 8, None, vertices=extra, spread=1)) and len(slices(lay)) == 5


@pytest.mark.parametrize("name", list(SEMIRINGS))
def test_levels_send_back_only_what_is_there(spark, name):
    s, lay = SEMIRINGS[name], L.build_pattern_slices(graph(spark, PATH), 4, 1)
    x = np.full(64, s.zero, s.dtype)
    x[0] = 0 if name == "tropical" else 1
    whole = {r.chunk_id: r.lanes for r in product.kernel_partials(lay, x, s).collect()}
    some = {r.chunk_id: r.lanes for r in product.packed_partials(lay, spark.sparkContext.broadcast((x, None, None)), s).collect()}
    assert some == {k: v for k, v in whole.items() if any(y != s.zero for y in v)} and len(some) == 1 < len(whole)


@pytest.mark.parametrize("name", list(SEMIRINGS))
@pytest.mark.parametrize("schedule", ["static", "dynamic"])
def test_deep_graphs(spark, name, schedule):
    lay = L.build_pattern_slices(graph(spark, PATH[:8]), 2, 1)
    got = bfs_dense(lay, 3, name, skip=False, schedule=schedule, workers=2)
    assert {r.vertex: r.dist for r in got.df.collect()} == {v: abs(v - 3) for v in range(9)}


def test_pairs_taken_as_distinct_are(spark):
    for name in catalog.ONCE:
        e = catalog.graph(spark, "/root/testdata/sf0.001", name)
        assert e.count() == e.distinct().count() > 0 and e.where("src = dst OR src IS NULL OR dst IS NULL").isEmpty()


def test_a_law_close_to_one_over_degree(spark):
    """Least squares give such laws at some scales of a graph; the bound is then no number that a double holds."""
    bound = cost.work_bound_powerlaw(10**6, 10**7, 8, 5, 0.5, 1.001)
    rows = experiments.Rows("W-20")
    rows.put("geo_tree", "power law", "bound", bound)
    assert math.isinf(bound) and spark.createDataFrame(list(rows), experiments.SCHEMA).where(F.col("value") > 1e308).count() == 1
    assert cost.work_bound_powerlaw(1000, 5000, 8, 3, 1.0, 2.0) == 3 * (6000 + 8 * 1000 * math.log(1000))
