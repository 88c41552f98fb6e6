"""Registered queries of the engine: for each a callable (spark, sf_dir) and, where SQL can say it, the oracle's statement."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphslices import catalog, cost, edges as E, experiments, extensions, layout as L, oracles as O, planner, product, relational, streaming
from graphslices.bfs import bfs_bag, bfs_csr, bfs_dense, bfs_direction, bfs_many, bfs_queue, bfs_recursive_sql, bfs_sparse, bfs_textbook_dense, recover_parents
from graphslices.semiring import REAL
from graphslices.session import cut

G = O.DEFAULT
SCOPES = [1, 8, 64, None]


def _prepared(spark: SparkSession, d: str, name: str = G) -> tuple[DataFrame, int]:
    e = cut(catalog.graph(spark, d, name))
    return e, E.pick_root(E.degrees(e))


def dense(name: str = G, semiring: str = "tropical", c: int = 8, sigma: int | None = None, tile: int = L.WIDE, valued: bool = False, keep=("vertex", "dist"), **options) -> Callable:
    def query(spark: SparkSession, d: str) -> DataFrame:
        e, root = _prepared(spark, d, name)
        lay = L.build_slices(e, c, sigma, valued=valued, tile_width=tile)
        return bfs_dense(lay, root, semiring, edges=e, **options).df.select(*keep)

    return query


def over_edges(f: Callable, name: str = G) -> Callable:
    """A traversal f(edges, root) as a query."""
    return lambda spark, d: f(*_prepared(spark, d, name))


def trace(name: str, c: int, sigma: int | None, skip: bool) -> Callable:
    def query(spark: SparkSession, d: str) -> DataFrame:
        e, root = _prepared(spark, d, name)
        got = bfs_dense(L.build_pattern_slices(e, c, sigma), root, skip=skip).trace
        return got.select("iter", "frontier", "slots", "skipped")

    return query


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Tropical traversal of pattern slices with skipping and tiles."""
    return dense(tile=64)(spark, d)


PARENTS = ("vertex", "dist", "parent")
Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def add(name: str, query: Callable, sql: str | None = None) -> None:
    Q[name] = query
    if sql:
        SQL[name] = sql


for _s in ("tropical", "boolean", "real", "selmax"):
    _keep = PARENTS if _s == "selmax" else ("vertex", "dist", "paths") if _s == "real" else ("vertex", "dist")
    _sql = O.parents() if _s == "selmax" else O.bfs(extra=", coalesce(bfs.paths, 0) AS paths") if _s == "real" else O.bfs()
    add(f"bfs_valued_{_s}_{G}", dense(semiring=_s, valued=True, skip=False, keep=_keep), _sql)
    add(f"bfs_pattern_{_s}_{G}", dense(semiring=_s, skip=False, keep=_keep), _sql)
    add(f"bfs_skip_{_s}_{G}", dense(semiring=_s, sigma=64, keep=_keep), _sql)
    add(f"bfs_tiles_{_s}_{G}", dense(semiring=_s, tile=32, c=32, keep=_keep), _sql)
    add(f"bfs_grid_{_s}_{G}", dense(semiring=_s, physical="grid", col_block=512, keep=_keep), _sql)
    add(f"bfs_relational_{_s}_{G}", dense(semiring=_s, physical="relational", keep=_keep), _sql)
add("bfs_recovered_boolean", dense(semiring="boolean", parents="recover", keep=PARENTS), O.parents())
add("bfs_static_schedule", dense(schedule="static", workers=4), O.bfs())
for _g in ("customer_part", "order_part", "copurchase", "geo_tree", "user_hour", "page_links", "shared_lines", "conv_chain", "event_chain", "knn", "kron", "er"):
    add(f"levels_{_g}", dense(_g, tile=256), O.bfs(_g))
add("selmax_parents_kron", dense("kron", "selmax", keep=PARENTS), O.parents("kron"))
for _n, _f in {
    "queue": bfs_queue, "queue_late_check": lambda e, r: bfs_queue(e, r, precheck=False), "bag": bfs_bag, "direction": bfs_direction,
    "sparse_sort": lambda e, r: bfs_sparse(e, r, "sort"), "sparse_radix": lambda e, r: bfs_sparse(e, r, "radix"), "sparse_hash": lambda e, r: bfs_sparse(e, r, "hash"),
    "csr": lambda e, r: bfs_csr(L.build_csr(e), r), "csr_unrolled": lambda e, r: bfs_csr(L.build_csr(e), r, "tropical", 4),
}.items():
    add(f"bfs_{_n}_{G}", over_edges(_f), O.bfs())
add("bfs_textbook_geo", over_edges(lambda e, r: bfs_textbook_dense(e, r), "geo_tree"), O.bfs("geo_tree"))
add("bfs_recursive_sql_geo", over_edges(lambda e, r: bfs_recursive_sql(e, r, 4), "geo_tree"), f"SELECT vertex, dist FROM ({O.bfs('geo_tree')}) WHERE dist IS NOT NULL")
add("bfs_queue_event_chain", over_edges(bfs_queue, "event_chain"), O.bfs("event_chain"))
add("path_lengths_conv_chain", over_edges(bfs_queue, "conv_chain"), O.bfs("conv_chain"))
for _t in ("max", "min"):
    add(f"parents_recovered_{_t}", over_edges(lambda e, r, t=_t: recover_parents(e, bfs_queue(e, r), t)), O.parents(tie=_t))


def many_roots(spark: SparkSession, d: str) -> DataFrame:
    """From the three vertices of highest degree."""
    e = cut(catalog.graph(spark, d, G))
    roots = [r.id for r in E.degrees(e).orderBy(F.desc("deg"), "id").limit(3).collect()]
    return bfs_many(L.build_pattern_slices(e, 8, None), roots).select("root", "vertex", "dist")


def planned(spark: SparkSession, d: str, name: str) -> DataFrame:
    e, root = _prepared(spark, d, name)
    layout = L.build_pattern_slices(e, 8, None)
    return planner.run(planner.rewrite(planner.plan_for(layout)), layout, e, root).df.select("vertex", "dist")


add("bfs_many_roots", many_roots, " UNION ALL ".join(f"SELECT * FROM ({O.bfs_ctes(G, f'(SELECT id FROM deg ORDER BY deg DESC, id LIMIT 1 OFFSET {k})')} SELECT (SELECT id FROM deg ORDER BY deg DESC, id LIMIT 1 OFFSET {k}) AS root, deg.id AS vertex, bfs.dist FROM deg LEFT JOIN bfs ON bfs.vertex = deg.id)" for k in range(3)))
add("planned_traversal", lambda s, d: planned(s, d, G), O.bfs())
add("planned_traversal_event_chain", lambda s, d: planned(s, d, "event_chain"), O.bfs("event_chain"))

# measures
add("degree_histogram", lambda s, d: E.degree_histogram(E.degrees(catalog.graph(s, d, G))), f"SELECT deg, count(*) AS cnt FROM {O.D_SP} GROUP BY deg")
add(
    "degree_summary", lambda s, d: E.degree_summary(E.degrees(catalog.graph(s, d, G))),
    f"SELECT count(*) AS n, cast(sum(deg) AS BIGINT) AS nnz, max(deg) AS max_deg, round(avg(deg), 6) AS slots_per_row, round(avg(deg) / 2, 6) AS edges_per_row FROM {O.D_SP}",
)
for _g in (G, "customer_part", "order_part", "kron", "er"):
    for _c in (8, 32):
        add(f"padding_by_sigma_{_g}_{_c}", lambda s, d, g=_g, c=_c: cost.padding_by_sigma(E.degrees(catalog.graph(s, d, g)), c, SCOPES), O.padding(_g, _c, SCOPES))
        add(f"storage_cells_{_g}_{_c}", lambda s, d, g=_g, c=_c: cost.storage_report(cost.padding_by_sigma(E.degrees(catalog.graph(s, d, g)), c, SCOPES)), O.storage(_g, _c, SCOPES))
add(
    "storage_ratio", lambda s, d: cost.layout_ratio(cost.storage_report(cost.padding_by_sigma(E.degrees(catalog.graph(s, d, G)), 8, SCOPES))),
    f"""SELECT c, sigma, {', '.join(f"round(max(cells) FILTER (layout = 'pattern') / max(cells) FILTER (layout = '{k}'), 6) AS to_{k}" for k in ('valued', 'al', 'csr'))} FROM ({O.storage(G, 8, SCOPES)}) GROUP BY c, sigma""",
)
add(
    "beats_adjacency_list", lambda s, d: cost.beats_adjacency_list(cost.padding_by_sigma(E.degrees(catalog.graph(s, d, "order_part")), 8, SCOPES)),
    f"SELECT c, sigma, round(pad_slots / n, 6) AS share, round(1 - 2 / c, 6) AS \"limit\", pad_slots / n < 1 - 2 / c AS beats FROM ({O.padding('order_part', 8, SCOPES)})",
)
add(
    "padding_bound", lambda s, d: cost.padding_bound(E.degree_summary(E.degrees(catalog.graph(s, d, G))), 8),
    f"SELECT max(deg) * 8 AS bound, greatest(cast(sum(deg) AS BIGINT), CASE WHEN count(*) >= 8 THEN max(deg) * 8 ELSE 0 END) AS least_slots FROM {O.D_SP}",
)
for _layout, _valued in (("pattern", False), ("valued", True)):
    add(
        f"cells_measured_{_layout}", lambda s, d, v=_valued: cost.storage_cells(L.build_slices(catalog.graph(s, d, G), 8, None, valued=v)),
        f"SELECT layout, cells AS cells_measured FROM ({O.storage(G, 8, [None])}) WHERE layout = '{_layout}'",
    )
for _g, _sg in ((G, None), ("kron", None), ("kron", 64), ("er", None), ("geo_tree", None)):
    for _k in (True, False):
        add(f"work_per_iteration_{'skip' if _k else 'noskip'}_{_g}_{_sg or 'n'}", trace(_g, 8, _sg, _k), O.work(_g, 8, _sg, _k))
add(
    "imbalance_static", lambda s, d: cost.imbalance(L.build_pattern_slices(catalog.graph(s, d, "kron"), 8, None), 4, "static"),
    f"""WITH {O._e('kron')}, {O.positions('kron', None)}, ch AS (SELECT pos // 8 AS ch, max(deg) * 8 AS slots FROM pos GROUP BY 1), w AS (SELECT ch * 4 // (SELECT count(*) FROM ch) AS worker, sum(slots) AS slots FROM ch GROUP BY 1)
        SELECT 4 AS workers, 'static' AS schedule, round(max(slots) * 4 / sum(slots), 6) AS imbalance FROM w""",
)
add("imbalance_dynamic", lambda s, d: cost.imbalance(L.build_pattern_slices(catalog.graph(s, d, "kron"), 8, None), 4, "dynamic"))
add("imbalance_tiled", lambda s, d: cost.imbalance(L.build_pattern_slices(catalog.graph(s, d, "kron"), 8, None, tile_width=32), 4, "tiled"), O.tiled_imbalance("kron", 8, 32, 4))


def amortized_slots(s: SparkSession, d: str) -> DataFrame:
    """The share of building in building and r runs, in slots touched instead of seconds: a build writes each slot once, a run reads what its levels read."""
    e, root = _prepared(s, d, G)
    layout = L.build_pattern_slices(e, 8, None)
    read = bfs_dense(layout, root).trace.agg(F.sum("slots")).first()[0]
    return cost.amortization(s, float(cost.product_slots(layout).first()[0]), float(read), [1, 10, 20])


def work_of_methods(s: SparkSession, d: str) -> DataFrame:
    e, root = _prepared(s, d, G)
    size = E.degree_summary(E.degrees(e)).first()
    return cost.work_table(s, size.n, size.nnz // 2, E.bfs_depth(E.reachable(bfs_queue(e, root))), 8, size.max_deg)


add(
    "amortization", amortized_slots,
    f"""WITH t AS ({O.work(G, 8, None, True)}), p AS ({O.padding(G, 8, [None])}) SELECT cast(r AS INTEGER) AS runs, round(slots / (slots + r * (SELECT sum(slots) FROM t)), 6) AS share FROM p, (VALUES (1), (10), (20)) v(r)""",
)
add("work_table", work_of_methods, O.work_table(G, 8))


def spoilt_parents(e: DataFrame, r: int) -> DataFrame:
    """A right result in which every fifth vertex names itself as its parent: what the check must find, and nothing else."""
    got = bfs_dense(L.build_pattern_slices(e, 8, None), r, "selmax").df
    return cost.invalid_parents(e, got.withColumn("parent", F.when((F.col("vertex") % 5 == 0) & F.col("dist").isNotNull(), F.col("vertex")).otherwise(F.col("parent"))))


def spoilt_levels(e: DataFrame, r: int) -> DataFrame:
    """Slices against a queue from whose result every seventh vertex of the second level is gone."""
    return cost.diff_results(bfs_dense(L.build_pattern_slices(e, 8, 64), r).df, bfs_queue(e, r).where("dist <> 2 OR vertex % 7 <> 0"))


add("invalid_parents", over_edges(spoilt_parents), f"SELECT vertex, dist, vertex AS parent FROM ({O.bfs()}) WHERE dist > 0 AND vertex % 5 = 0")
add("different_levels", over_edges(spoilt_levels), f"SELECT vertex, dist AS dist_a, cast(NULL AS INTEGER) AS dist_b FROM ({O.bfs()}) WHERE dist = 2 AND vertex % 7 = 0")
add("reachable_vertices", over_edges(lambda e, r: E.reachable(bfs_queue(e, r)), "page_links"), f"SELECT vertex, dist FROM ({O.bfs('page_links')}) WHERE dist IS NOT NULL")
add(
    "trace_work_kron", over_edges(lambda e, r: (lambda lay: cost.trace_work(bfs_dense(lay, r), lay))(L.build_pattern_slices(e, 8, None)), "kron"),
    f"SELECT t.iter, t.frontier, t.slots, t.skipped, cast(8 * ceil(p.n / 8) AS BIGINT) AS test_work, round(skipped / ceil(p.n / 8), 6) AS skipped_share FROM ({O.work('kron', 8, None, True)}) t, ({O.padding('kron', 8, [None])}) p",
)
add(
    "bytes_avoided_kron", over_edges(lambda e, r: (lambda lay: cost.bytes_avoided(lay, bfs_dense(lay, r)))(L.build_pattern_slices(e, 8, None)), O.GIVEN["kron"]),
    f"SELECT t.iter, 8 * t.slots AS col_bytes, 8 * t.slots AS val_bytes, 16 * (p.slots - t.slots) AS skipped_bytes FROM ({O.work(O.GIVEN['kron'], 8, None, True)}) t, ({O.padding(O.GIVEN['kron'], 8, [None])}) p",
)

# products


def _degree_vector(layout: L.Layout) -> DataFrame:
    return layout.positions.select("pos", F.col("deg").cast("double").alias("x"))


def _by_vertex(y: DataFrame, layout: L.Layout) -> DataFrame:
    return y.join(layout.positions, F.col("row") == F.col("pos")).select(F.col("id").alias("vertex"), F.col("y").cast("bigint").alias("y"))


def mv_slices_query(kind: str) -> Callable:
    def query(s: SparkSession, d: str) -> DataFrame:
        lay = L.build_slices(catalog.graph(s, d, G), 8, None, valued=kind == "valued", tile_width=64)
        x = _degree_vector(lay)
        if kind == "grid":
            return _by_vertex(product.mv_grid(L.build_grid(lay, 256, 1000), x, REAL), lay)
        return _by_vertex(product.mv_tiles(lay, x, REAL) if kind == "tiles" else product.mv_slices(lay, x, REAL), lay)

    return query


def mv_csr_query(k: int | None) -> Callable:
    def query(s: SparkSession, d: str) -> DataFrame:
        e = cut(catalog.graph(s, d, G))
        x = E.degrees(e).select(F.col("id").alias("pos"), F.col("deg").cast("double").alias("x"))
        y = product.mv_csr_unrolled(L.build_csr(e), x, REAL, k) if k else product.mv_csr(L.build_csr(e), x, REAL)
        return y.select(F.col("row").alias("vertex"), F.col("y").cast("bigint").alias("y"))

    return query


def mv_weighted(s: SparkSession, d: str) -> DataFrame:
    e = cut(experiments.weighted_edges(s, d))
    lay = L.build_valued_slices(e, 8, None, "w")
    y = product.mv_tiles(lay, _degree_vector(lay), REAL, weighted=True)
    return y.join(lay.positions, F.col("row") == F.col("pos")).select(F.col("id").alias("vertex"), F.round("y", 4).alias("y"))


_PRODUCT = f"SELECT src AS vertex, cast(sum(deg) AS BIGINT) AS y FROM ({O.E_SP}) JOIN {O.D_SP} ON id = dst GROUP BY src"
for _k in ("pattern", "valued", "tiles", "grid"):
    add(f"mv_{_k}", mv_slices_query(_k), _PRODUCT)
add("mv_csr", mv_csr_query(None), _PRODUCT)
add("mv_unrolled", mv_csr_query(4), _PRODUCT)
add("mv_weighted", mv_weighted, O.weighted_product())
add("er_edges", lambda s, d: catalog.graph(s, d, "er"), O.graph_sql("er"))
add("kron_edges", lambda s, d: catalog.graph(s, d, "kron"), O.graph_sql("kron"))
add("csr_offsets", lambda s, d: L.build_csr(catalog.graph(s, d, G)).select("vertex", F.size("nbrs").alias("k"), "offset"),
    f"SELECT id AS vertex, cast(deg AS INTEGER) AS k, cast(coalesce(sum(deg) OVER (ORDER BY id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS \"offset\" FROM {O.D_SP}")

# extensions
add("odd_cycle_edges_er", over_edges(lambda e, r: extensions.odd_cycle_edges(e, bfs_queue(e, r)), "er"), f"{O.bfs_ctes('er')} SELECT src, dst FROM e JOIN bfs a ON a.vertex = src JOIN bfs b ON b.vertex = dst WHERE src < dst AND (a.dist - b.dist) % 2 = 0")
add("pagerank_supplier_part", over_edges(lambda e, r: extensions.pagerank(L.build_pattern_slices(e, 8, None), 5).withColumn("rank", F.round("rank", 12))), O.pagerank(G, 5))
add("betweenness_supplier_part", over_edges(lambda e, r: extensions.betweenness_from_root(e, bfs_dense(L.build_pattern_slices(e, 8, None), r, "real").df).withColumn("dependency", F.round("dependency", 9))), O.betweenness(G, 8))

for _n, _sql in O.RELATIONAL.items():
    add(_n, getattr(relational, _n), _sql)
add("neighbour_counts_approx", relational.neighbour_counts_approx)
for _n in ("stream_dedupe", "stream_enrich", "stream_coactivity", "stream_distance"):
    add(_n, getattr(streaming, _n), O.STREAMS[_n])
for _k in ("tumbling", "sliding", "session"):
    add(f"stream_degrees_{_k}", lambda s, d, k=_k: streaming.stream_degrees(s, d, k).select(F.col("start").cast("timestamp_ntz").alias("start"), F.col("finish").cast("timestamp_ntz").alias("finish"), "src", "deg"), O.STREAMS[f"stream_degrees_{_k}"])
for _w in experiments.WORKLOADS:
    add(f"workload_{_w.lower().replace('-', '_')}", lambda s, d, w=_w: experiments.run(s, d, w))
for _w, (_options, _sql) in O.COUNTED.items():
    add(f"counted_{_w.lower().replace('-', '_')}", lambda s, d, w=_w, o=_options: experiments.counted(s, d, w, **o), _sql)
