"""Graphs with hubs and streams of few types, at sizes at which all pairs would be too many."""

import random

from pyspark.sql import functions as F

from graphslices import relational, streaming
from graphslices.bfs import bfs_recursive_sql, bfs_textbook_dense


def star(spark, leaves, hub=0):
    """A hub and its leaves, both directions."""
    out = spark.range(1, leaves + 1).select(F.lit(hub).cast("long").alias("src"), F.col("id").alias("dst"))
    return out.unionByName(out.select(F.col("dst").alias("src"), F.col("src").alias("dst")))


def test_textbook_product_beyond_tiny_graphs(spark):
    e = star(spark, 6000).unionByName(spark.createDataFrame([(6000, 9000), (9000, 6000), (9100, 9200), (9200, 9100)], "src long, dst long"))
    got = {r.vertex: r.dist for r in bfs_textbook_dense(e, 0).collect()}
    assert got == {0: 0} | dict.fromkeys(range(1, 6001), 1) | {9000: 2, 9100: None, 9200: None}


def test_recursive_statement_past_a_hub(spark):
    before = spark.conf.get("spark.sql.cteRecursionRowLimit")
    got = {r.vertex: r.dist for r in bfs_recursive_sql(star(spark, 1500), 7, 4).collect()}
    assert got == {7: 0, 0: 1} | {v: 2 for v in range(1, 1501) if v != 7}
    assert spark.conf.get("spark.sql.cteRecursionRowLimit") == before


def test_two_hop_counts(spark):
    rng = random.Random(5)
    pairs = {(a, b) for a, b in ((rng.randint(0, 60), rng.randint(0, 60)) for _ in range(60)) if a != b}
    both = pairs | {(b, a) for a, b in pairs}
    want = {}
    for a in {a for a, _ in both}:
        far = {z for m in {y for x, y in both if x == a} for x, z in both if x == m and z != a}
        if far:
            want[a] = len(far)
    got = relational.two_hop_counts(spark.createDataFrame(sorted(both), "src long, dst long"))
    assert {r.src: r.two_hop for r in got.collect()} == want


def test_two_hop_of_a_large_hub(spark):
    got = relational.two_hop_counts(star(spark, 100_000))
    assert [tuple(r) for r in got.groupBy("two_hop").count().collect()] == [(99_999, 100_000)]


def test_coactivity_joins_by_slots_of_time(spark):
    rng = random.Random(6)
    rows = [(i, rng.randint(0, 30), "purchase", rng.choice((600 * rng.randint(-40, 40), rng.randint(-20_000, 20_000)))) for i in range(400)]
    df = spark.createDataFrame(rows, "event_id long, src long, event_type string, s long").withColumn("time", F.timestamp_seconds("s"))
    got = streaming.coactivity(df, df)
    want = sorted((x[1], y[1], x[3], y[3]) for x in rows for y in rows if x[1] < y[1] and abs(x[3] - y[3]) <= 300)
    assert sorted(tuple(r) for r in got.select("a", "b", F.unix_seconds("at"), F.unix_seconds("bt")).collect()) == want
    keys = [line for line in got._jdf.queryExecution().sparkPlan().toString().splitlines() if "Join" in line]
    assert all("sa" in k and "sb" in k for k in keys) and keys
