"""Counted workloads on graphs of the tables: they follow the tables, and count without runs what timed runs count."""

import os

import pytest

import __spark_entry__ as entry
from graphslices import experiments
from test_more import metric

SMALL, LARGER = "/root/testdata/sf0.001", "/root/testdata/sf0.01"
pytestmark = pytest.mark.skipif(not os.path.isdir(SMALL), reason="needs the test tables")


@pytest.mark.parametrize("name", ["counted_w_02", "counted_w_03", "counted_w_06", "counted_w_19", "degree_tail_regression", "bytes_avoided_kron"])
def test_results_follow_the_tables(spark, name):
    run = entry.queries()[name]
    assert {tuple(r) for r in run(spark, SMALL).collect()} != {tuple(r) for r in run(spark, LARGER).collect()}


def test_counting_runs_nothing_for_its_seconds(spark, monkeypatch):
    options = {"given": {"kron": "page_links"}, "scopes": (8, None)}
    timed = metric(experiments.run(spark, SMALL, "W-02", **options), "pad_slots")
    monkeypatch.setattr(experiments, "bfs_dense", None)
    assert metric(experiments.counted(spark, SMALL, "W-02", **options), "pad_slots") == timed and len(timed) == 2
