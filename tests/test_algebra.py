"""Semirings, lane functions and products."""

import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from graphslices import cost, kernels, lanes, layout as L, product
from graphslices.schema import INF
from graphslices.semiring import BOOLEAN, REAL, SELMAX, SEMIRINGS, TROPICAL
from test_layout import CASES, graph

VALUES = {"tropical": st.integers(0, 50) | st.just(INF), "real": st.integers(0, 9), "boolean": st.integers(0, 1), "selmax": st.integers(0, 40)}


@pytest.mark.parametrize("name", SEMIRINGS)
@settings(max_examples=60, deadline=None)
@given(data=st.data())
def test_axioms(name, data):
    s = SEMIRINGS[name]
    a, b, c = (data.draw(VALUES[name]) for _ in range(3))
    assert s.plus(a, b) == s.plus(b, a) and s.plus(a, s.plus(b, c)) == s.plus(s.plus(a, b), c) and s.plus(a, s.zero) == a
    assert s.times(a, s.times(b, c)) == s.times(s.times(a, b), c) and s.times(a, s.one) == a and s.times(s.one, a) == a
    assert s.pad_value == s.zero


def test_post_step_operations():
    assert {k: (s.post_ops, s.post_stores) for k, s in SEMIRINGS.items()} == {"tropical": (0, 0), "real": (6, 2), "boolean": (6, 2), "selmax": (4, 2)}


def test_negation_example(spark):
    a = F.array(*map(F.lit, (0, 7, 0)))
    row = spark.range(1).select(lanes.complement(a).alias("no"), lanes.support(a).alias("yes")).first()
    assert (row.no, row.yes) == ([1, 0, 1], [0, 1, 0])
    assert kernels.complement(np.array([0, 7, 0])).tolist() == [1, 0, 1]


def test_lane_functions_in_both_forms(spark):
    rng = random.Random(3)
    a, b, m = ([rng.randint(0, 5) for _ in range(8)] for _ in range(3))
    row = spark.createDataFrame([(a, b, m)], "a array<bigint>, b array<bigint>, m array<bigint>").select(
        lanes.lane_cmp(F.col("a"), F.col("b")).alias("eq"), lanes.lane_cmp(F.col("a"), F.col("b"), "!=").alias("ne"), lanes.lane_blend(F.col("a"), F.col("b"), F.col("m")).alias("blend"),
        lanes.lane_min(F.col("a"), F.col("b")).alias("lo"), lanes.lane_max(F.col("a"), F.col("b")).alias("hi"), lanes.lane_add(F.col("a"), F.col("b")).alias("add"), lanes.lane_mul(F.col("a"), F.col("b")).alias("mul"),
        lanes.lane_and(F.col("a"), F.col("b")).alias("and_"), lanes.lane_or(F.col("a"), F.col("b")).alias("or_"), lanes.lane_load(F.col("a"), 1, 4).alias("load"), lanes.lane_cast(F.col("a")).alias("cast"),
        lanes.lane_gather(F.col("a"), F.array(F.lit(2), F.lit(-1)), INF).alias("gather"), lanes.lane_add(F.array(F.lit(INF).cast("bigint")), F.array(F.lit(1).cast("bigint")), True).alias("sat"),
    ).first()
    x, y, k = map(np.array, (a, b, m))
    assert row.eq == kernels.lane_cmp(x, y).tolist() and row.ne == kernels.lane_cmp(x, y, "!=").tolist() and row.blend == kernels.lane_blend(x, y, k).tolist()
    assert row.lo == np.minimum(x, y).tolist() and row.hi == np.maximum(x, y).tolist() and row["add"] == (x + y).tolist() and row.mul == (x * y).tolist()
    assert row.and_ == ((x != 0) & (y != 0)).astype(int).tolist() and row.or_ == ((x != 0) | (y != 0)).astype(int).tolist()
    assert row.load == a[4:8] and row.cast == list(map(float, a)) and row.gather == [a[2], INF] and row.sat == [INF]


@pytest.mark.parametrize("s", [TROPICAL, REAL, BOOLEAN, SELMAX], ids=lambda s: s.name)
def test_products_agree(spark, s):
    e = graph(spark, CASES["row lengths"] + CASES["clique"])
    lay = L.build_slices(e, 4, None, valued=True, tile_width=3)
    rng = random.Random(1)
    values = {r.id: rng.randint(1, 5) if s is not BOOLEAN else 1 for r in lay.positions.collect()}
    vec = spark.createDataFrame(list(values.items()), "id long, x long")
    near = {}
    for r in e.collect():
        near.setdefault(r.src, []).append(values[r.dst])
    want = {v: {"tropical": lambda q: min(q) + 1, "real": sum, "boolean": max, "selmax": max}[s.name](q) for v, q in near.items()}
    at = vec.join(lay.positions, "id").select("pos", "x")
    by_id = vec.withColumnRenamed("id", "pos")
    place = {r.pos: r.id for r in lay.positions.collect()}
    for y in (product.mv_slices(lay, at, s), product.mv_tiles(lay, at, s), product.mv_grid(L.build_grid(lay, 5, 6), at, s)):
        assert {place[r.row]: r.y for r in y.collect() if r.row in place} == want
    csr = L.build_csr(e)
    for y in (product.mv_csr(csr, by_id, s), product.mv_csr_unrolled(csr, by_id, s, 4), product.mv_sparse(e, by_id, s)):
        assert {r.row: r.y for r in y.collect()} == want
    full = product.mv_dense(e, spark.createDataFrame([(v,) for v in values], "id long"), by_id, s)
    assert {r.row: r.y for r in full.collect()} == want


def test_vector_size_is_checked(spark):
    with pytest.raises(ValueError):
        product.dense_vector(spark.createDataFrame([], "pos long, x long"), 10**9, BOOLEAN)


def test_implied_values(spark):
    got = spark.range(1).select(L.implied_values(F.array(F.lit(3), F.lit(-1)), 0, 1).alias("v")).first().v
    assert got == [1, 0]


def test_bounds_and_amortisation(spark):
    shares = {r.runs: r.share for r in cost.amortization(spark, 0.95, 0.95 / 0.21, [1, 10, 20]).collect()}
    assert 0.17 < shares[1] < 0.18 and 0.02 < shares[10] < 0.021 and shares[20] < 0.05
    assert cost.work_bound_general(10, 40, 8, 5, 3) == 3 * 90
    with pytest.raises(ValueError):
        cost.largest_degree_powerlaw(10, 1.0, 1.0)
    assert cost.work_bound_er(1000, 0.5, 8, 2) > cost.work_bound_er(1000, 0.001, 8, 2)
    limits = {r.c: r.limit for r in cost.beats_adjacency_list(spark.createDataFrame([(8, 1, 10, 5), (16, 1, 10, 5), (32, 1, 10, 5)], "c int, sigma long, n long, pad_slots long")).collect()}
    assert limits == {8: 0.75, 16: 0.875, 32: 0.9375}


def test_grid_product_moves_no_neighbours(spark):
    """With broadcast joins off, nothing is exchanged between the tiles' scan and the product."""
    e = spark.createDataFrame([(i, j) for i in range(40) for j in range(40) if (i * j) % 7 == 1], "src long, dst long")
    lay = L.build_pattern_slices(e, 4, None)
    grid = L.build_grid(lay, 8, 20)
    assert grid.parts.where("parts > 1").count() > 0
    old = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        y = product.mv_grid(grid, lay.positions.select("pos", F.lit(1.0).alias("x")), REAL)
        plan = y._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", old)
    lines = plan.split("\n")
    scan = next(i for i, x in enumerate(lines) if "FileScan parquet" in x and "graphslices_grid" in x)
    up = [x for x in lines[next(i for i, x in enumerate(lines) if "FlatMapCoGroupsInArrow" in x) + 1 : scan]]
    assert up and not any("Exchange" in x for x in up), plan
    assert y.agg(F.sum("y")).first()[0] == e.count()
