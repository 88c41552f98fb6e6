"""Traversals against plain Python, all forms alike; rulings on doubtful points."""

import pytest
from pyspark.sql import functions as F

from graphslices import cost, edges as E, layout as L
from graphslices.bfs import bfs_bag, bfs_csr, bfs_dense, bfs_direction, bfs_queue, bfs_recursive_sql, bfs_sparse, bfs_textbook_dense, recover_parents
from graphslices.planner import TraversalPlan, explain, rewrite
from graphslices.session import cut
from test_layout import EXAMPLE, graph, ids

GRAPH = EXAMPLE + [(7, 8), (2, 9), (9, 10), (10, 4), (5, 11), (11, 12)]


def plain(pairs, root):
    near = {}
    for a, b in pairs:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    dist, queue = {root: 0}, [root]
    for u in queue:
        for v in near[u]:
            if v not in dist:
                dist[v] = dist[u] + 1
                queue.append(v)
    parent = {v: v if not d else max(u for u in near[v] if dist.get(u) == d - 1) for v, d in dist.items()}
    paths = {root: 1}
    for v in queue[1:]:
        paths[v] = sum(paths[u] for u in near[v] if dist.get(u) == dist[v] - 1)
    return near, dist, parent, paths


@pytest.fixture(scope="module")
def known(spark):
    return cut(graph(spark, GRAPH)), plain(GRAPH, 1)


@pytest.mark.parametrize("semiring", ["tropical", "boolean", "real", "selmax"])
@pytest.mark.parametrize("physical", ["kernel", "relational", "grid"])
def test_dense(spark, known, semiring, physical):
    e, (near, dist, parent, paths) = known
    for c, sigma, tile, skip in ((8, None, 4096, True), (2, 2, 1, False), (4, 1, 2, True)):
        lay = L.build_pattern_slices(e, c, sigma, tile_width=tile)
        got = bfs_dense(lay, 1, semiring, skip, parents="recover", edges=e, physical=physical, col_block=3).df.collect()
        assert {r.vertex: r.dist for r in got} == {v: dist.get(v) for v in near}
        assert {r.vertex: r.parent for r in got} == {v: parent.get(v) for v in near}
        if semiring == "real":
            assert {r.vertex: r.paths for r in got} == {v: paths.get(v, 0) for v in near}


def test_example_work_with_and_without_skipping(spark):
    lay = L.build_pattern_slices(graph(spark, EXAMPLE), 2, None, vertices=ids(spark, [6]))
    slots = lambda skip: [r.slots for r in bfs_dense(lay, 1, skip=skip).trace.orderBy("iter").collect()]
    assert slots(True) == [12, 8, 2, 2]
    assert slots(False) == [12, 12, 12, 12]
    got = {r.vertex: (r.dist, r.parent) for r in bfs_dense(lay, 1, "selmax").df.collect()}
    assert got == {1: (0, 1), 2: (1, 1), 3: (1, 1), 4: (2, 3), 5: (3, 4), 6: (None, None)}


@pytest.mark.parametrize("name", ["queue", "late", "bag", "direction", "up", "sort", "radix", "hash", "csr", "unrolled", "selmax", "dense", "sql"])
def test_baselines(spark, known, name):
    e, (near, dist, _, _) = known
    run = {
        "queue": lambda: bfs_queue(e, 1), "late": lambda: bfs_queue(e, 1, precheck=False), "bag": lambda: bfs_bag(e, 1, 3), "direction": lambda: bfs_direction(e, 1),
        "up": lambda: bfs_direction(e, 1, alpha=1000, beta=1000), "sort": lambda: bfs_sparse(e, 1, "sort"), "radix": lambda: bfs_sparse(e, 1, "radix"), "hash": lambda: bfs_sparse(e, 1, "hash"),
        "csr": lambda: bfs_csr(L.build_csr(e), 1), "unrolled": lambda: bfs_csr(L.build_csr(e), 1, "tropical", 4), "selmax": lambda: bfs_csr(L.build_csr(e), 1, "selmax"),
        "dense": lambda: bfs_textbook_dense(e, 1), "sql": lambda: bfs_recursive_sql(e, 1, 8),
    }[name]().collect()
    want = dist if name == "sql" else {v: dist.get(v) for v in near}
    assert {r.vertex: r.dist for r in run} == want


def test_recovery_skips_unreachable_and_obeys_ties(spark, known):
    e, (near, dist, parent, _) = known
    d = bfs_queue(e, 1)
    assert {r.vertex: r.parent for r in recover_parents(e, d).collect()} == {v: parent.get(v) for v in near}
    least = {r.vertex: r.parent for r in recover_parents(e, d, "min").collect()}
    assert least[4] == 2 and least[7] is None and least[1] == 1


def test_vertex_zero_and_roots(spark):
    e = graph(spark, [(0, 1), (0, 2), (2, 3)])
    lay = L.build_pattern_slices(e, 2, None)
    assert {r.vertex: r.parent for r in bfs_dense(lay, 3, "selmax").df.collect()} == {3: 3, 2: 3, 0: 2, 1: 0}
    with pytest.raises(ValueError):
        bfs_dense(lay, 99)
    alone = L.build_pattern_slices(e, 2, None, vertices=ids(spark, [50]))
    assert {r.vertex: r.dist for r in bfs_dense(alone, 50).df.collect()} == {0: None, 1: None, 2: None, 3: None, 50: 0}


def test_static_schedule_and_limits(spark, known):
    e, (near, dist, _, _) = known
    lay = L.build_pattern_slices(e, 2, None)
    got = bfs_dense(lay, 1, schedule="static", workers=3, max_iter=1).df.collect()
    assert {r.vertex for r in got if r.dist is not None} == {v for v, d in dist.items() if d <= 1}


def test_measures_of_exactness(spark, known):
    e, _ = known
    good = bfs_dense(L.build_pattern_slices(e, 4, None), 1, "selmax").df
    assert cost.diff_results(good, bfs_queue(e, 1)).count() == 0
    assert cost.invalid_parents(e, good).count() == 0
    wrong = good.withColumn("parent", F.when(F.col("vertex") == 4, 12).otherwise(F.col("parent"))).withColumn("dist", F.when(F.col("vertex") == 5, 1).otherwise(F.col("dist")))
    assert {r.vertex for r in cost.invalid_parents(e, wrong).collect()} >= {4, 5}
    assert [r.vertex for r in cost.diff_results(good, wrong).collect()] == [5]


def test_plan_rules():
    p = rewrite(TraversalPlan(n=1000, nnz=5000, widest=10_000))
    assert (p.values, p.skip, p.tile_width, p.gather, p.method) == (False, True, 4096, "kernel", "dense")
    assert rewrite(TraversalPlan(n=10**9, nnz=1)).gather == "grid"
    assert rewrite(TraversalPlan(n=10, nnz=9, depth_guess=500)).method == "queue"
    assert "SkipSettled" in explain(p)
