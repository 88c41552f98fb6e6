"""Streams against their batch twins, extensions against plain code, workloads, and the behaviour that the experiments report."""

import random
from collections import deque

import pytest
from pyspark.sql import functions as F

from graphslices import catalog, cost, edges as E, experiments, extensions, layout as L, streaming
from graphslices.bfs import bfs_dense, bfs_many, bfs_queue
from graphslices.session import cut
from test_layout import EXAMPLE, graph

SMALL = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def files(spark, tmp_path_factory):
    """Events of two hours in four files, some late and some repeated."""
    path = str(tmp_path_factory.mktemp("events") / "e")
    rows = [(i, i % 5, f"2024-01-01 0{i % 3}:{i % 60:02d}:00", "purchase" if i % 4 else "view", 1.0, "{}") for i in range(120)]
    df = spark.createDataFrame(rows, "event_id long, user_id long, ts string, event_type string, value double, props string").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    df.repartition(4, "event_id").write.parquet(path)
    return path


@pytest.mark.parametrize("kind", ["tumbling", "sliding"])
def test_windows_equal_their_batch_twin(spark, files, kind):
    stream = streaming.degrees_in_windows(streaming.timed_edges(streaming.stream_source(spark, files, 1), "30 days"), kind)
    got = streaming.drain_to_table(stream, "complete").collect()
    twin = streaming.degrees_in_windows(streaming.timed_edges(spark.read.parquet(files)), kind).collect()
    assert sorted(map(tuple, got)) == sorted(map(tuple, twin)) and got


def test_sessions_append_when_the_watermark_has_passed(spark, files):
    stream = streaming.degrees_in_windows(streaming.timed_edges(streaming.stream_source(spark, files, 1), "10 minutes"), "session")
    got = {tuple(r) for r in streaming.drain_to_table(stream).collect()}
    assert all(r[3] > 0 for r in got)


def test_late_rows_are_dropped_behind_the_watermark(spark, tmp_path):
    path = str(tmp_path / "late")
    for k, stamp in enumerate(["2024-01-01 00:00:00", "2024-01-02 00:00:00", "2024-01-02 00:10:00", "2024-01-01 00:20:00"]):
        spark.createDataFrame([(k, 1, stamp, "view")], "event_id long, user_id long, ts string, event_type string").withColumn("ts", F.col("ts").cast("timestamp_ntz")).coalesce(1).write.mode("append").parquet(path)
        import time

        time.sleep(1.1)  # files are taken in order of their times
    stream = streaming.degrees_in_windows(streaming.timed_edges(streaming.stream_source(spark, path, 1), "1 hour"))
    got = streaming.drain_to_table(stream).collect()
    assert [(r.src, r.deg) for r in got] == [(1, 1)]


def test_distances_follow_insertions(spark):
    rng = random.Random(2)
    edges = [(rng.randint(0, 14), rng.randint(0, 14)) for _ in range(24)]
    edges = [(a, b) for a, b in edges if a != b]
    state = streaming.MinDistance(spark, 0)
    for k in range(0, len(edges), 8):
        state.insert(spark.createDataFrame(edges[k : k + 8], "src long, dst long"))
        near = {}
        for a, b in edges[: k + 8]:
            near.setdefault(a, set()).add(b)
            near.setdefault(b, set()).add(a)
        dist, queue = {0: 0}, deque([0])
        while queue:
            u = queue.popleft()
            for v in near.get(u, ()):
                if v not in dist:
                    dist[v] = dist[u] + 1
                    queue.append(v)
        assert {r.vertex: r.dist for r in state.dist.collect()} == dist


def test_pagerank_and_betweenness(spark):
    e = cut(graph(spark, EXAMPLE))
    lay = L.build_pattern_slices(e, 2, None)
    near = {1: [2, 3], 2: [1, 4], 3: [1, 4], 4: [2, 3, 5], 5: [4]}
    rank = {v: 0.2 for v in near}
    for _ in range(6):
        rank = {v: 0.03 + 0.85 * sum(rank[u] / len(near[u]) for u in near[v]) for v in near}
    got = {r.vertex: r["rank"] for r in extensions.pagerank(lay, 6).collect()}
    assert all(abs(got[v] - rank[v]) < 1e-9 for v in near)
    dep = {r.vertex: r.dependency for r in extensions.betweenness_from_root(e, bfs_dense(lay, 1, "real").df).collect()}
    assert dep == {1: 4.0, 2: 1.0, 3: 1.0, 4: 1.0, 5: 0.0}


def test_uses_of_distances(spark):
    even, odd = graph(spark, [(i, (i + 1) % 6) for i in range(6)]), graph(spark, [(i, (i + 1) % 5) for i in range(5)])
    assert extensions.odd_cycle_edges(even, bfs_queue(even, 0)).count() == 0
    assert extensions.odd_cycle_edges(odd, bfs_queue(odd, 0)).count() == 1
    assert extensions.double_sweep(graph(spark, [(i, i + 1) for i in range(6)])) == 6
    flow = spark.createDataFrame([(0, 1), (1, 2), (0, 3), (3, 4), (4, 2), (2, 5)], "src long, dst long")
    assert extensions.augmenting_path(flow, 0, 5) == [0, 1, 2, 5] and extensions.augmenting_path(flow, 5, 0) == []
    roots = bfs_many(L.build_pattern_slices(even, 2, None), [0, 3]).where("vertex = 0").collect()
    assert {r.root: r.dist for r in roots} == {0: 0, 3: 3}
    lay = L.build_pattern_slices(even, 2, None)
    grid = L.grid_tiles(lay, 2)
    assert extensions.active_column_blocks(grid, spark.createDataFrame([(0, 1)], "pos long, x long"), 2).count() < grid.count()


def test_project_pairs(spark):
    df = spark.createDataFrame([(1, "x"), (2, "x"), (3, "x"), (3, "y"), (1, "y")], "l long, r string")
    assert sorted(map(tuple, E.project_pairs(df, "l", "r").collect())) == [(1, 2), (1, 3), (2, 3)]


def test_edge_files(spark, tmp_path):
    from graphslices.relational import read_edges, write_edges

    e = graph(spark, EXAMPLE)
    for fmt in ("csv", "json", "orc", "parquet"):
        write_edges(e, str(tmp_path / fmt), fmt)
        assert {tuple(r) for r in read_edges(spark, str(tmp_path / fmt), fmt).collect()} == {tuple(r) for r in e.collect()}


def metric(df, name):
    return {(r.graph, r.variant, r.sigma, r.iter): r.value for r in df.where(F.col("metric") == name).collect()}


def test_skipping_saves_work_on_skewed_graphs(spark):
    got = metric(experiments.run(spark, SMALL, "W-04", graphs=("kron", "er")), "slots")
    total = lambda g, v: sum(x for (a, b, s, _), x in got.items() if a == g and b == v and s > 1000)
    kron, er = total("kron", "skip") / total("kron", "plain"), total("er", "skip") / total("er", "plain")
    assert kron < 0.5 and kron < er <= 1
    assert all(got[g, "skip", s, i] <= got[g, "plain", s, i] for g, v, s, i in got if v == "skip" and (g, "plain", s, i) in got)


def test_padding_falls_with_the_scope_and_pattern_halves_values(spark):
    got = metric(experiments.run(spark, SMALL, "W-17", graphs=("kron", "er"), widths=(8,)), "cells")
    for g in ("kron", "er"):
        by = {s: x for (a, v, s, _), x in got.items() if a == g and v == "pattern"}
        assert by[max(by)] == min(by.values()) and by[1] == by[8] == max(by.values())
        for s in by:
            assert abs(by[s] / got[g, "valued", s, None] - 0.5) < 0.02


def test_wide_scopes_unbalance_static_schedules_and_tiles_help(spark):
    e = catalog.graph(spark, SMALL, "kron")
    whole = L.build_pattern_slices(e, 8, None)
    static = cost.imbalance(whole, 4, "static").first().imbalance
    assert static > 2 > cost.imbalance(L.tile_slices(whole, 32), 4, "tiled").first().imbalance
    assert cost.imbalance(whole, 4, "dynamic").first().imbalance < 1.2


@pytest.mark.parametrize("w", ["W-06", "W-16", "W-20", "W-23"])
def test_workloads_run(spark, w):
    df = experiments.run(spark, SMALL, w)
    assert df.count() > 0 and df.where("value IS NULL").count() == 0
    if w == "W-20":
        rows = {(r.graph, r.metric, r.variant): r.value for r in df.collect()}
        assert rows["kron", "work", "measured"] <= rows["kron", "bound", "general"]
    if w == "W-23":
        assert len({r.value for r in df.where("metric = 'sum'").collect()}) == 1
