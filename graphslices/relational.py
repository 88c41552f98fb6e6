"""Operators around traversals on the given tables: edge extraction, joins, aggregates, windows, sets and functions. Each takes (spark, sf_dir)."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphslices import catalog, edges as E, layout as L, product
from graphslices.bfs import bfs_dense, bfs_queue
from graphslices.lanes import complement, lane_add, lane_blend, lane_cmp, lane_gather, lane_load, lane_max, lane_min, support
from graphslices.semiring import REAL, TROPICAL
from graphslices.session import cut, ship

SEGMENTS = "c_mktsegment"


def _t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return catalog.load_table(spark, d, name)


def _graph(spark: SparkSession, d: str, name: str = "supplier_part") -> DataFrame:
    return catalog.graph(spark, d, name)


def levels(spark: SparkSession, d: str, name: str = "supplier_part") -> DataFrame:
    """(vertex, dist) from the graph's root by the flagship traversal."""
    e = cut(_graph(spark, d, name))
    lay = L.build_pattern_slices(e, 8, None)
    return bfs_dense(lay, E.pick_root(E.degrees(e))).df.select("vertex", "dist")


# -- scans and projections -----------------------------------------------------------------------------------------------------------------


def scan_table(spark: SparkSession, d: str) -> DataFrame:
    """Two columns of lineitem under a pushed filter."""
    return _t(spark, d, "lineitem").where("l_quantity > 45").select("l_orderkey", "l_partkey")


def layout_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    """Edges written as slices, reopened and unpacked."""
    from graphslices.session import cut  # noqa: F401  (sets the shared folder where it is unset)

    lay = L.build_pattern_slices(_graph(spark, d), 8, None)
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    import uuid

    path = f"{base}/layout-{uuid.uuid4().hex}"
    L.save_layout(lay, path)
    return L.slices_to_edges(L.open_layout(spark, path))


def edge_file_roundtrip(spark: SparkSession, d: str, fmt: str = "csv") -> DataFrame:
    e = cut(_graph(spark, d, "geo_tree"))
    import uuid

    path = f"{spark.conf.get('spark.checkpoint.dir', None) or spark.sparkContext.getCheckpointDir()}/edges-{uuid.uuid4().hex}"
    write_edges(e, path, fmt)
    return read_edges(spark, path, fmt)


def write_edges(edges: DataFrame, path: str, fmt: str) -> None:
    edges.select("src", "dst").write.format(fmt).save(path)


def read_edges(spark: SparkSession, path: str, fmt: str) -> DataFrame:
    """Edge lists as CSV, JSON, ORC or Parquet, with a given schema: nothing is inferred."""
    return spark.read.schema("src long, dst long").format(fmt).load(path)


def generated_edges(spark: SparkSession, d: str) -> DataFrame:
    return catalog.graph(spark, d, "kron")


def page_link_edges(spark: SparkSession, d: str) -> DataFrame:
    return _graph(spark, d, "page_links")


def encode_bipartite(spark: SparkSession, d: str) -> DataFrame:
    return _t(spark, d, "lineitem").select((F.col("l_suppkey") * 2).alias("a"), (F.col("l_partkey") * 2 + 1).alias("b")).distinct()


def filtered_edges(spark: SparkSession, d: str) -> DataFrame:
    li = _t(spark, d, "lineitem").where((F.col("l_quantity").between(10, 30)) & (F.col("l_shipdate") >= F.lit("1995-01-01").cast("timestamp_ntz")))
    return E.normalize_edges(li.select((F.col("l_suppkey") * 2).alias("a"), (F.col("l_partkey") * 2 + 1).alias("b")), "a", "b")


def induced_subgraph(spark: SparkSession, d: str) -> DataFrame:
    """customer_part among customers of one market segment."""
    keep = _t(spark, d, "customer").where(F.col(SEGMENTS) == "BUILDING").select((F.col("c_custkey") * 2).alias("src"))
    e = _graph(spark, d, "customer_part").where("src % 2 = 0")
    return e.join(keep, "src", "left_semi")


def null_safe_levels(spark: SparkSession, d: str) -> DataFrame:
    dist = levels(spark, d, "geo_tree")
    return dist.select("vertex", F.coalesce("dist", F.lit(-1)).alias("level"), F.when(F.equal_null("dist", F.lit(None).cast("int")), "unreached").otherwise("reached").alias("state"))


def levels_with_attributes(spark: SparkSession, d: str) -> DataFrame:
    """Customers of customer_part by nation and level."""
    c = _t(spark, d, "customer").select((F.col("c_custkey") * 2).alias("vertex"), "c_nationkey")
    return levels(spark, d, "customer_part").join(c, "vertex").groupBy("c_nationkey", "dist").agg(F.count("*").alias("customers"))


# -- joins ---------------------------------------------------------------------------------------------------------------------------------


def _frontier(e: DataFrame) -> DataFrame:
    """The ten vertices of highest degree."""
    return E.degrees(e).orderBy(F.desc("deg"), "id").limit(10).select(F.col("id").alias("src"))


def frontier_broadcast_join(spark: SparkSession, d: str) -> DataFrame:
    e = _graph(spark, d)
    return e.join(F.broadcast(_frontier(e)), "src").groupBy("src").agg(F.count("*").alias("near"))  # ten rows


def frontier_hash_join(spark: SparkSession, d: str) -> DataFrame:
    e = _graph(spark, d)
    return e.join(_frontier(e).hint("shuffle_hash"), "src").select("dst").distinct()


def grid_merge_join(spark: SparkSession, d: str) -> DataFrame:
    """Products of places: each row's neighbours meet the vector by merged, sorted sides."""
    e = _graph(spark, d)
    x = E.degrees(e).select(F.col("id").alias("dst"), F.col("deg").alias("x"))
    return e.join(x.hint("merge"), "dst").groupBy("src").agg(F.sum("x").alias("y"))


def dense_cross(spark: SparkSession, d: str) -> DataFrame:
    """The dense product over nations and regions only."""
    n, r = _t(spark, d, "nation").select("n_nationkey", "n_regionkey"), _t(spark, d, "region").select("r_regionkey")
    return n.crossJoin(r).select("n_nationkey", "r_regionkey", (F.col("n_regionkey") == F.col("r_regionkey")).cast("int").alias("a"))


def copurchase_theta(spark: SparkSession, d: str) -> DataFrame:
    li = _t(spark, d, "lineitem").select("l_orderkey", "l_partkey").distinct()
    o = li.withColumnsRenamed({"l_orderkey": "o", "l_partkey": "b"})
    return li.join(o, (F.col("l_orderkey") == F.col("o")) & (F.col("l_partkey") < F.col("b"))).groupBy(F.col("l_partkey").alias("a")).agg(F.countDistinct("b").alias("later"))


def position_range_join(spark: SparkSession, d: str) -> DataFrame:
    """Places meet ranges of 64 places by the range's number, not by comparing bounds."""
    pos = L.sorted_positions(E.degrees(_graph(spark, d)), None)
    n = pos.count()
    ranges = spark.range(0, -(-n // 64)).select(F.col("id").alias("block"), (F.col("id") * 64).alias("first"))
    return pos.withColumn("block", F.floor(F.col("pos") / 64)).join(ranges, "block").groupBy("block", "first").agg(F.sum("deg").alias("deg"))


def edges_as_of(spark: SparkSession, d: str) -> DataFrame:
    """The last event of each user's before or at each of their purchases' events: a union with a forward fill."""
    ev = _t(spark, d, "events")
    left = ev.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("l"), F.lit(None).cast("long").alias("r"))
    right = ev.where("event_type <> 'purchase'").groupBy("user_id", "ts").agg(F.max("event_id").alias("r")).select("user_id", "ts", F.lit(None).cast("long").alias("l"), "r")
    w = Window.partitionBy("user_id").orderBy("ts", F.col("l").isNotNull()).rowsBetween(Window.unboundedPreceding, 0)
    return left.unionByName(right).withColumn("seen", F.last("r", ignorenulls=True).over(w)).where("l IS NOT NULL").select(F.col("l").alias("event_id"), "seen")


def coactivity_interval(spark: SparkSession, d: str) -> DataFrame:
    """Pairs of users with purchases less than five minutes apart: equal or neighbouring buckets, then the exact test."""
    ev = _t(spark, d, "events").where("event_type = 'purchase'").select("user_id", F.timestamp_diff("SECOND", F.lit("1970-01-01").cast("timestamp_ntz"), F.col("ts")).alias("s"))
    a = ev.select(F.col("user_id").alias("a"), F.col("s").alias("sa"), F.floor(F.col("s") / 300).alias("b"))
    other = ev.select(F.col("user_id").alias("c"), F.col("s").alias("sc"), F.explode(F.expr("sequence(floor(s / 300) - 1, floor(s / 300) + 1)")).alias("b"))
    return a.join(other, "b").where("a < c AND abs(sa - sc) < 300").select("a", "c").distinct()


def unsettled_semi(spark: SparkSession, d: str) -> DataFrame:
    """Chunks with a vertex beyond level 1."""
    e = cut(_graph(spark, d))
    lay = L.build_pattern_slices(e, 8, None)
    got = bfs_dense(lay, E.pick_root(E.degrees(e)), max_iter=1).df
    left = got.where("dist IS NULL").join(lay.positions.select(F.col("id").alias("vertex"), "pos"), "vertex").select(F.floor(F.col("pos") / 8).alias("chunk_id"))
    return lay.slices.select("chunk_id", "width").join(left, "chunk_id", "left_semi")


def unvisited_anti(spark: SparkSession, d: str) -> DataFrame:
    e = cut(_graph(spark, d, "geo_tree"))
    seen = bfs_queue(e, E.pick_root(E.degrees(e)), max_iter=2).where("dist IS NOT NULL").select(F.col("vertex").alias("id"))
    return E.vertex_set(e).join(seen, "id", "left_anti")


def compare_levels_outer(spark: SparkSession, d: str) -> DataFrame:
    """Levels of two traversals from different roots side by side."""
    e = cut(_graph(spark, d, "geo_tree"))
    a = bfs_queue(e, E.pick_root(E.degrees(e))).where("dist IS NOT NULL").select("vertex", F.col("dist").alias("da"))
    b = bfs_queue(e, 20000000).where("dist IS NOT NULL").select("vertex", F.col("dist").alias("db"))
    return a.join(b, "vertex", "full_outer").groupBy("da", "db").agg(F.count("*").alias("vertices"))


def two_hop(spark: SparkSession, d: str) -> DataFrame:
    return two_hop_counts(cut(_graph(spark, d, "geo_tree")))


def two_hop_counts(e: DataFrame) -> DataFrame:
    """(src, two_hop): other vertices that share a neighbour with a vertex, over edges in both directions. Leaves of one neighbour reach the same vertices, so they go as one row with their number: a hub of k leaves costs one row, not k * k."""
    leaf = e.groupBy("src").agg(F.count("*").alias("deg"), F.min("dst").alias("hub")).select("src", F.when(F.col("deg") == 1, F.col("hub")).alias("hub"))
    named = cut(leaf.withColumn("kind", F.when(F.col("hub").isNull(), F.struct(F.lit(0).alias("leaves"), F.col("src").alias("id"))).otherwise(F.struct(F.lit(1).alias("leaves"), F.col("hub").alias("id")))).select("src", "kind"))
    size = named.groupBy("kind").agg(F.count("*").alias("n"))
    to = cut(e.join(named, "src").select(F.col("dst").alias("m"), "kind").distinct().join(size, "kind"))
    # a kind meets itself through any neighbour: all its vertices but the one that asks are counted
    near = to.select(F.col("kind").alias("own"), "m").join(to, "m").select("own", "kind", "n").distinct()
    counts = near.groupBy("own").agg((F.sum("n") - 1).alias("two_hop"))
    return named.join(counts, F.col("kind") == F.col("own")).where("two_hop > 0").select("src", "two_hop")


def triangle_count(spark: SparkSession, d: str) -> DataFrame:
    """Triangles of the generated random graph: each is counted from its least vertex."""
    up = _graph(spark, d, "er").where("src < dst")
    wedge = up.join(up.select(F.col("src").alias("s2"), F.col("dst").alias("d2")), (F.col("src") == F.col("s2")) & (F.col("dst") < F.col("d2")))
    return wedge.join(up.select(F.col("src").alias("p"), F.col("dst").alias("q")), (F.col("dst") == F.col("p")) & (F.col("d2") == F.col("q"))).agg(F.count("*").alias("triangles"))


# -- aggregates ----------------------------------------------------------------------------------------------------------------------------


def product_hash_agg(spark: SparkSession, d: str) -> DataFrame:
    e = _graph(spark, d)
    x = E.degrees(e).select(F.col("id").alias("pos"), F.col("deg").alias("x"))
    return product.mv_sparse(e, x, TROPICAL)


def product_sort_agg(spark: SparkSession, d: str) -> DataFrame:
    """Sums of neighbours' degrees by ordering the input by its key and closing each run of equal keys."""
    e = _graph(spark, d)
    x = e.join(E.degrees(e).select(F.col("id").alias("dst"), "deg"), "dst")
    w = Window.partitionBy("src").orderBy("dst")
    run = x.withColumn("y", F.sum("deg").over(w.rowsBetween(Window.unboundedPreceding, 0))).withColumn("nxt", F.lead("dst").over(w))
    return run.where("nxt IS NULL").select(F.col("src").alias("row"), "y")


def neighbour_counts(spark: SparkSession, d: str) -> DataFrame:
    li = _t(spark, d, "lineitem")
    return li.groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("parts"), F.count("*").alias("lines"))


def neighbour_counts_approx(spark: SparkSession, d: str) -> DataFrame:
    """Approximate distinct counts beside exact ones."""
    got = _t(spark, d, "lineitem").groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("exact"), F.approx_count_distinct("l_partkey", 0.02).alias("approx"))
    return got.withColumn("error", F.abs(F.col("approx") - F.col("exact")) / F.col("exact"))


def _segments(spark: SparkSession, d: str) -> DataFrame:
    c = _t(spark, d, "customer").select((F.col("c_custkey") * 2).alias("vertex"), SEGMENTS)
    return levels(spark, d, "customer_part").join(c, "vertex")


def level_cube(spark: SparkSession, d: str) -> DataFrame:
    return _segments(spark, d).cube("dist", SEGMENTS).agg(F.count("*").alias("n"))


def level_rollup(spark: SparkSession, d: str) -> DataFrame:
    return _segments(spark, d).rollup("dist", SEGMENTS).agg(F.count("*").alias("n"))


def level_grouping_sets(spark: SparkSession, d: str) -> DataFrame:
    return _segments(spark, d).groupingSets([["dist"], [SEGMENTS]], "dist", SEGMENTS).agg(F.count("*").alias("n")).select("dist", SEGMENTS, "n")


def adjacency_arrays(spark: SparkSession, d: str) -> DataFrame:
    return L.build_adjacency(_graph(spark, d, "geo_tree")).select("vertex", F.size("nbrs").cast("long").alias("k"), F.array_join("nbrs", ",").alias("nbrs"))


def parent_by_max(spark: SparkSession, d: str) -> DataFrame:
    return _graph(spark, d).groupBy("dst").agg(F.max_by("src", "src").alias("largest"), F.min_by("src", "src").alias("least"))


def degree_percentiles(spark: SparkSession, d: str) -> DataFrame:
    deg = E.degrees(_graph(spark, d))
    return deg.agg(*[F.percentile("deg", p).alias(f"p{int(100 * p)}") for p in (0.25, 0.5, 0.75, 0.99)])


def trace_pivot(spark: SparkSession, d: str) -> DataFrame:
    """Newly reached vertices by level, a column for each semiring."""
    e = cut(_graph(spark, d))
    lay, root, out = L.build_pattern_slices(e, 8, None), E.pick_root(E.degrees(e)), None
    for name in ("tropical", "boolean", "real", "selmax"):
        one = bfs_dense(lay, root, name).trace.where("frontier > 0").select("iter", "frontier", F.lit(name).alias("semiring"))
        out = one if out is None else out.unionByName(one)
    return out.groupBy("iter").pivot("semiring", ["tropical", "boolean", "real", "selmax"]).agg(F.first("frontier"))


def level_conditional_counts(spark: SparkSession, d: str) -> DataFrame:
    return levels(spark, d).agg(F.count_if(F.col("dist") <= 1).alias("near"), F.count_if(F.col("dist") > 1).alias("far"), F.count_if(F.col("vertex") % 2 == 0).alias("left_side"))


def degree_tail_regression(spark: SparkSession, d: str) -> DataFrame:
    from graphslices.cost import fit_power_law

    return fit_power_law(E.degree_histogram(E.degrees(_graph(spark, d, "page_links"))))


# -- windows, order, sets ------------------------------------------------------------------------------------------------------------------


def positions_ranked(spark: SparkSession, d: str) -> DataFrame:
    deg = E.degrees(_graph(spark, d)).withColumn("block", F.floor(F.col("id") / 256))
    w = Window.partitionBy("block").orderBy(F.desc("deg"))
    return deg.select("id", F.row_number().over(Window.partitionBy("block").orderBy(F.desc("deg"), "id")).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"))


def static_assignment(spark: SparkSession, d: str) -> DataFrame:
    deg = E.degrees(_graph(spark, d)).withColumn("side", F.col("id") % 2)
    w = Window.partitionBy("side").orderBy(F.desc("deg"), "id")
    return deg.select("id", F.ntile(4).over(w).alias("worker"), F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"))


def event_chain_edges(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return _t(spark, d, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"))


def chunk_offsets(spark: SparkSession, d: str) -> DataFrame:
    return L.chunk_directory(L.build_pattern_slices(_graph(spark, d), 8, None))


def recent_degree(spark: SparkSession, d: str) -> DataFrame:
    """Events of a user in the hour up to each event."""
    ev = _t(spark, d, "events").select("event_id", "user_id", F.timestamp_diff("SECOND", F.lit("1970-01-01").cast("timestamp_ntz"), F.col("ts")).alias("s"))
    w = Window.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)
    return ev.select("event_id", F.count("*").over(w).alias("recent"))


def last_edge_value(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return _t(spark, d, "events").select("user_id", F.first_value("event_id").over(w).alias("first"), F.last_value("event_id").over(w).alias("last"), F.nth_value("event_id", 2).over(w).alias("second")).distinct()


def global_degree_order(spark: SparkSession, d: str) -> DataFrame:
    return L.sorted_positions(E.degrees(_graph(spark, d)), None).select("id", "deg", "pos")


def partition_sorted_edges(spark: SparkSession, d: str) -> DataFrame:
    from graphslices.bfs.frontier import sort_dedupe

    return sort_dedupe(_graph(spark, d).select(F.col("dst").alias("vertex")))


def top_degrees(spark: SparkSession, d: str) -> DataFrame:
    return E.degrees(_graph(spark, d)).orderBy(F.desc("deg"), "id").offset(5).limit(20)


def farthest_per_group(spark: SparkSession, d: str) -> DataFrame:
    """The three farthest customers of each segment."""
    w = Window.partitionBy(SEGMENTS).orderBy(F.desc_nulls_last("dist"), "vertex")
    return _segments(spark, d).withColumn("rn", F.row_number().over(w)).where("rn <= 3").select(SEGMENTS, "vertex", "dist", "rn")


def symmetrised_edges(spark: SparkSession, d: str) -> DataFrame:
    p = catalog.pairs(spark, d, "geo_tree")
    return p.select(F.col("a").alias("src"), F.col("b").alias("dst")).unionByName(p.select(F.col("b").alias("src"), F.col("a").alias("dst"))).distinct()


def edge_snapshot_diff(spark: SparkSession, d: str) -> DataFrame:
    """Pairs of one year's shipments that the year before lacks."""
    li = _t(spark, d, "lineitem").select("l_suppkey", "l_partkey", F.year("l_shipdate").alias("y"))
    year = lambda y: li.where(F.col("y") == y).select("l_suppkey", "l_partkey")
    return year(1996).subtract(year(1995))


def edge_snapshot_diff_all(spark: SparkSession, d: str) -> DataFrame:
    li = _t(spark, d, "lineitem").select("l_suppkey", F.year("l_shipdate").alias("y"))
    year = lambda y: li.where(F.col("y") == y).select("l_suppkey")
    return year(1996).exceptAll(year(1995)).groupBy("l_suppkey").agg(F.count("*").alias("more"))


def common_neighbours_intersect(spark: SparkSession, d: str) -> DataFrame:
    e = _graph(spark, d)
    two = [r.id for r in E.degrees(e).orderBy(F.desc("deg"), "id").limit(2).collect()]
    near = lambda v: e.where(F.col("src") == v).select("dst")
    return near(two[0]).intersect(near(two[1]))


# -- scalar functions ----------------------------------------------------------------------------------------------------------------------


def url_parts(spark: SparkSession, d: str) -> DataFrame:
    host = F.lower(F.regexp_extract("url", "://([^/?#]*)", 1))
    return _t(spark, d, "pages").select("page_id", host.alias("host"), F.element_at(F.split(host, r"\."), -1).alias("top"), F.md5("url").alias("digest"))


def hourly_vertices(spark: SparkSession, d: str) -> DataFrame:
    ev = _t(spark, d, "events")
    return ev.groupBy(F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("hour")).agg(F.countDistinct("user_id").alias("users"))


def bound_math(spark: SparkSession, d: str) -> DataFrame:
    deg = E.degrees(_graph(spark, d))
    return deg.select(
        "id", F.round(F.log2("deg"), 9).alias("lg"), F.pow(F.col("deg").cast("double"), F.lit(2.0)).alias("sq"), F.ceil(F.col("deg") / 8).alias("chunks"), F.shiftleft("deg", 2).alias("four"),
        F.greatest("deg", F.lit(100)).alias("top"), (F.col("deg") % 8).alias("rest"),
    )


def lane_arrays(spark: SparkSession, d: str) -> DataFrame:
    """Every lane operation on arrays of sixteen degrees, over all vertices."""
    deg = E.degrees(_graph(spark, d))
    g = deg.groupBy(F.floor(F.col("id") / 16).alias("g")).agg(F.sort_array(F.collect_list("deg")).alias("v"))  # sixteen ids a group
    one = g.withColumn("a", F.slice(F.concat("v", F.array_repeat(F.lit(0).cast("long"), 16)), 1, 16)).withColumn("b", F.reverse("a"))
    a, b = F.col("a"), F.col("b")
    eq = lane_cmp(a, b)
    total = lambda x: F.aggregate(x, F.lit(0).cast("long"), lambda s, y: s + y)
    ops = {"lo": lane_min(a, b), "hi": lane_max(a, b), "add": lane_add(a, b), "eq": eq, "pick": lane_blend(a, b, eq), "no": complement(a), "yes": support(a), "load": lane_load(a, 0, 2), "got": lane_gather(a, F.array(F.lit(0).cast("long"), F.lit(-1).cast("long")), 0)}
    return one.select("g", *[total(v).alias(k) for k, v in ops.items()])


def slot_maps(spark: SparkSession, d: str) -> DataFrame:
    """Regions' nations by slot as maps, those of even slots kept."""
    n = _t(spark, d, "nation").groupBy("n_regionkey").agg(F.sort_array(F.collect_list("n_nationkey")).alias("ks"))
    m = F.map_filter(F.map_from_arrays(F.sequence(F.lit(0), F.size("ks") - 1), "ks"), lambda k, v: k % 2 == 0)
    return n.select("n_regionkey", F.explode(F.map_entries(m)).alias("e")).select("n_regionkey", F.col("e.key").alias("slot"), F.col("e.value").alias("nation"))


def props_edges(spark: SparkSession, d: str) -> DataFrame:
    ev = _t(spark, d, "events")
    k = F.from_json("props", "k int")["k"]
    return ev.select(F.col("user_id").alias("a"), k.alias("b")).where("b IS NOT NULL").groupBy("a", "b").agg(F.count("*").alias("n"))


def knn_edges(spark: SparkSession, d: str, k: int = 4, block: int = 4096) -> DataFrame:
    """Each vector's k nearest others by cosine, symmetrised: blocks of vectors are compared in one task each pair of blocks."""
    ship(spark)
    v = _t(spark, d, "embeddings").select(F.col("vec_id").cast("long").alias("id"), F.col("embedding").cast("array<double>").alias("v"))
    blocks = -(-v.count() // block)
    own = F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int")
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    sides = v.select("id", "v", own.alias("p"), every.alias("q"), F.lit(0).alias("side")).unionByName(v.select("id", "v", every.alias("p"), own.alias("q"), F.lit(1).alias("side")))

    def near(g):
        import numpy as np
        import pandas as pd

        a, b = g[g.side == 0], g[g.side == 1]
        if not len(a) or not len(b):
            return pd.DataFrame({"src": [], "dst": [], "s": []}).astype({"src": "int64", "dst": "int64", "s": "float64"})
        x, y = np.stack(a.v.to_numpy()), np.stack(b.v.to_numpy())
        s = (x @ y.T) / np.linalg.norm(x, axis=1)[:, None] / np.linalg.norm(y, axis=1)
        s[a.id.to_numpy()[:, None] == b.id.to_numpy()] = -np.inf
        top = np.argsort(-s, axis=1, kind="stable")[:, : k + 4]
        return pd.DataFrame({"src": np.repeat(a.id.to_numpy(), top.shape[1]), "dst": b.id.to_numpy()[top].ravel(), "s": np.take_along_axis(s, top, 1).ravel()})

    got = sides.groupBy("p", "q").applyInPandas(near, "src long, dst long, s double")
    best = got.withColumn("rn", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("s"), "dst"))).where((F.col("rn") <= k) & (F.col("s") > -2))
    return E.normalize_edges(best)


def packed_bit_frontier(spark: SparkSession, d: str) -> DataFrame:
    """Level 1 as words of 63 bits."""
    near = levels(spark, d).where("dist = 1")
    return near.groupBy(F.floor(F.col("vertex") / 63).alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(vertex % 63 AS INT))")).alias("bits")).select("word", "bits", F.bit_count("bits").cast("int").alias("n"))


# -- functions of one's own ----------------------------------------------------------------------------------------------------------------


def kernel_map(spark: SparkSession, d: str) -> DataFrame:
    """(chunk_id, widest, cells) by an Arrow function over slices."""
    ship(spark)
    lay = L.build_pattern_slices(_graph(spark, d), 8, None)

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa
        import pyarrow.compute as pc

        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pc.list_value_length(b.column(1)).cast(pa.int64())], names=["chunk_id", "cells"])

    return lay.slices.select("chunk_id", "col").mapInArrow(run, "chunk_id long, cells long").groupBy("chunk_id").agg(F.sum("cells").alias("cells"))


def lane_udf(spark: SparkSession, d: str) -> DataFrame:
    """Logical negation of a parity vector by a vectorised function."""

    @F.pandas_udf("long")
    def negate(v):
        return (v == 0).astype("int64")

    return E.degrees(_graph(spark, d)).select("id", negate(F.col("deg") % 2).alias("even"))


def lane_merge(spark: SparkSession, d: str) -> DataFrame:
    """Degrees as a product with the vector of ones, tiles merged lane by lane."""
    lay = L.build_pattern_slices(_graph(spark, d), 8, None, tile_width=16)
    ones = lay.positions.select("pos", F.lit(1.0).alias("x"))
    y = product.mv_tiles(lay, ones, REAL)
    return y.join(lay.positions, F.col("row") == F.col("pos")).select("id", F.col("y").cast("long").alias("deg"))


def register_sql(spark: SparkSession) -> None:
    """unpack_chunk(chunk_id, c, col) as a table function for SQL."""

    @F.udtf(returnType="row bigint, col bigint")
    class UnpackChunk:
        def eval(self, chunk_id: int, c: int, col: list):
            for i, x in enumerate(col):
                if x >= 0:
                    yield chunk_id * c + i % c, x

    spark.udtf.register("unpack_chunk", UnpackChunk)


def unpack_chunk(spark: SparkSession, d: str) -> DataFrame:
    """(row, k): neighbours of each place, by the table function in a lateral join."""
    register_sql(spark)
    lay = L.build_pattern_slices(_graph(spark, d, "geo_tree"), 8, None)
    return spark.sql("SELECT u.row, count(*) AS k FROM {s} t, LATERAL unpack_chunk(t.chunk_id, 8, t.col) u GROUP BY u.row", s=lay.slices)
