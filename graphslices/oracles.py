"""DuckDB SQL of the engine's queries, from the same graph definitions."""

from __future__ import annotations

from graphslices.catalog import graph_sql

DEFAULT = "supplier_part"


def _e(name: str) -> str:
    return f"e AS MATERIALIZED ({graph_sql(name)}), deg AS MATERIALIZED (SELECT src AS id, count(*) AS deg FROM e GROUP BY src), root AS MATERIALIZED (SELECT id AS r FROM deg ORDER BY deg DESC, id LIMIT 1)"


def bfs_ctes(name: str = DEFAULT, root: str | None = None) -> str:
    """WITH clauses e, deg, root and bfs(vertex, dist, paths); each vertex enters once, in its level."""
    start = root or "(SELECT r FROM root)"
    return f"""WITH RECURSIVE {_e(name)}, bfs(vertex, dist, paths) USING KEY (vertex) AS (
        SELECT cast({start} AS BIGINT), 0, cast(1 AS DOUBLE) UNION ALL
        SELECT e.dst, b.dist + 1, sum(b.paths) FROM bfs b JOIN e ON e.src = b.vertex LEFT JOIN recurring.bfs r ON r.vertex = e.dst WHERE r.vertex IS NULL GROUP BY e.dst, b.dist)"""


def bfs(name: str = DEFAULT, extra: str = "") -> str:
    """(vertex, dist) of every vertex, and more columns."""
    return f"{bfs_ctes(name)} SELECT deg.id AS vertex, bfs.dist{extra} FROM deg LEFT JOIN bfs ON bfs.vertex = deg.id"


def bfs_from(name: str, root: str) -> str:
    """(vertex, dist) of what a root reaches."""
    return f"{bfs_ctes(name, root)} SELECT vertex, dist FROM bfs"


def parents(name: str = DEFAULT, tie: str = "max", paths: bool = False) -> str:
    return f"""{bfs_ctes(name)}, up AS (SELECT e.dst AS vertex, {tie}(e.src) AS parent FROM e JOIN bfs a ON a.vertex = e.src JOIN bfs b ON b.vertex = e.dst WHERE a.dist = b.dist - 1 GROUP BY e.dst)
        SELECT deg.id AS vertex, bfs.dist, CASE WHEN bfs.dist = 0 THEN deg.id ELSE up.parent END AS parent FROM deg LEFT JOIN bfs ON bfs.vertex = deg.id LEFT JOIN up ON up.vertex = deg.id"""


def positions(name: str, sigma: int | None) -> str:
    """CTEs with pos(id, deg, pos)."""
    if sigma is None:
        place = "row_number() OVER (ORDER BY deg DESC, id) - 1"
    elif sigma == 1:
        place = "row_number() OVER (ORDER BY id) - 1"
    else:
        place = f"(rk // {sigma}) * {sigma} + row_number() OVER (PARTITION BY rk // {sigma} ORDER BY deg DESC, id) - 1"
    return f"ranked AS (SELECT id, deg, row_number() OVER (ORDER BY id) - 1 AS rk FROM deg), pos AS MATERIALIZED (SELECT id, deg, {place} AS pos FROM ranked)"


def padding(name: str, c: int, sigmas: list[int | None]) -> str:
    """(c, sigma, n, nnz, slots, pad_slots)."""
    parts = []
    for k, s in enumerate(sigmas):
        p = positions(name, s).replace("ranked", f"ranked{k}").replace("pos AS MATERIALIZED", f"pos{k} AS MATERIALIZED")
        parts.append((p, f"""SELECT {c} AS c, cast({s or 0} AS BIGINT) AS sigma, cast(sum(k) AS BIGINT) AS n, cast(sum(s) AS BIGINT) AS nnz, cast(sum(w) * {c} AS BIGINT) AS slots, cast(sum(w) * {c} - sum(s) AS BIGINT) AS pad_slots
            FROM (SELECT max(deg) AS w, sum(deg) AS s, count(*) AS k FROM pos{k} GROUP BY pos // {c})"""))
    return f"WITH {_e(name)}, {', '.join(p for p, _ in parts)} {' UNION ALL '.join(q for _, q in parts)}"


def storage(name: str, c: int, sigmas: list[int | None]) -> str:
    ch = "cast(ceil(n / c) AS BIGINT)"
    forms = {
        "al": ("nnz + n", "nnz + n"), "csr": ("2 * nnz + n", "2 * nnz + n"), "valued": (f"2 * (nnz + pad_slots) + 2 * {ch}", "2 * nnz + 2 * n / c + pad_slots"),
        "pattern": (f"nnz + pad_slots + 2 * {ch}", "nnz + 2 * n / c + pad_slots"),
    }
    return " UNION ALL ".join(
        f"SELECT c, sigma, '{k}' AS layout, cast({a} AS BIGINT) AS cells, round(cast({b} AS DOUBLE), 6) AS cells_formula FROM ({padding(name, c, sigmas)})" for k, (a, b) in forms.items()
    )


def work(name: str, c: int, sigma: int | None, skip: bool) -> str:
    """(iter, frontier, slots, skipped): a chunk is read until the level in which its last vertex is reached has passed."""
    alive = "last IS NULL OR last >= i" if skip else "true"
    return f"""{bfs_ctes(name)}, {positions(name, sigma)}, chunk AS (
          SELECT pos // {c} AS ch, max(pos.deg) * {c} AS slots, CASE WHEN count(*) = count(bfs.dist) THEN max(bfs.dist) END AS last FROM pos LEFT JOIN bfs ON bfs.vertex = pos.id GROUP BY 1),
        depth AS (SELECT max(dist) AS d, (SELECT count(*) FROM deg) = count(*) AS whole FROM bfs), it AS (SELECT unnest(range(1, d + 1 + CASE WHEN whole THEN 0 ELSE 1 END)) AS i FROM depth)
        SELECT cast(i AS INTEGER) AS iter, (SELECT count(*) FROM bfs WHERE dist = i) AS frontier, cast(coalesce(sum(slots) FILTER ({alive}), 0) AS BIGINT) AS slots,
          count(*) FILTER (NOT ({alive})) AS skipped FROM it, chunk GROUP BY i"""


LI = "FROM lineitem"
SEG = f"""({bfs_ctes('customer_part')} SELECT c.c_mktsegment, b.dist, b.vertex, c.c_nationkey FROM (SELECT deg.id AS vertex, bfs.dist FROM deg LEFT JOIN bfs ON bfs.vertex = deg.id) b JOIN customer c ON 2 * c.c_custkey = b.vertex)"""
E_SP = graph_sql(DEFAULT)
D_SP = f"(SELECT src AS id, count(*) AS deg FROM ({E_SP}) GROUP BY src)"
EPOCH = "cast(floor(epoch(ts)) AS BIGINT)"

RELATIONAL = {
    "scan_table": "SELECT l_orderkey, l_partkey FROM lineitem WHERE l_quantity > 45",
    "layout_roundtrip": E_SP,
    "edge_file_roundtrip": graph_sql("geo_tree"),
    "generated_edges": graph_sql("kron"),
    "page_link_edges": graph_sql("page_links"),
    "encode_bipartite": "SELECT DISTINCT 2 * l_suppkey AS a, 2 * l_partkey + 1 AS b FROM lineitem",
    "filtered_edges": "WITH p AS (SELECT DISTINCT 2 * l_suppkey AS a, 2 * l_partkey + 1 AS b FROM lineitem WHERE l_quantity BETWEEN 10 AND 30 AND l_shipdate >= TIMESTAMP '1995-01-01') SELECT a AS src, b AS dst FROM p UNION SELECT b, a FROM p",
    "induced_subgraph": f"SELECT src, dst FROM ({graph_sql('customer_part')}) WHERE src % 2 = 0 AND src // 2 IN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'BUILDING')",
    "null_safe_levels": f"SELECT vertex, coalesce(dist, -1) AS level, CASE WHEN dist IS NULL THEN 'unreached' ELSE 'reached' END AS state FROM ({bfs('geo_tree')})",
    "levels_with_attributes": f"SELECT c_nationkey, dist, count(*) AS customers FROM {SEG} GROUP BY ALL",
    "frontier_broadcast_join": f"SELECT id AS src, deg AS near FROM {D_SP} ORDER BY deg DESC, id LIMIT 10",
    "frontier_hash_join": f"SELECT DISTINCT dst FROM ({E_SP}) WHERE src IN (SELECT id FROM {D_SP} ORDER BY deg DESC, id LIMIT 10)",
    "grid_merge_join": f"SELECT src, cast(sum(deg) AS BIGINT) AS y FROM ({E_SP}) JOIN {D_SP} ON id = dst GROUP BY src",
    "dense_cross": "SELECT n_nationkey, r_regionkey, cast(n_regionkey = r_regionkey AS INTEGER) AS a FROM nation, region",
    "copurchase_theta": "SELECT x.l_partkey AS a, count(DISTINCT y.l_partkey) AS later FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey AND x.l_partkey < y.l_partkey GROUP BY 1",
    "position_range_join": f"SELECT pos // 64 AS block, (pos // 64) * 64 AS first, cast(sum(deg) AS BIGINT) AS deg FROM (SELECT deg, row_number() OVER (ORDER BY deg DESC, id) - 1 AS pos FROM {D_SP}) GROUP BY ALL",
    "edges_as_of": """WITH l AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'purchase'), r AS (SELECT user_id, ts, max(event_id) AS seen FROM events WHERE event_type <> 'purchase' GROUP BY ALL)
        SELECT event_id, seen FROM l ASOF LEFT JOIN r ON l.user_id = r.user_id AND l.ts >= r.ts""",
    "coactivity_interval": f"WITH p AS (SELECT user_id, {EPOCH} AS s FROM events WHERE event_type = 'purchase') SELECT DISTINCT x.user_id AS a, y.user_id AS c FROM p x JOIN p y ON x.user_id < y.user_id AND abs(x.s - y.s) < 300",
    "unsettled_semi": f"""{bfs_ctes()}, {positions(DEFAULT, None)}, ch AS (SELECT pos // 8 AS chunk_id, cast(max(pos.deg) AS INTEGER) AS width, bool_or(bfs.dist IS NULL OR bfs.dist > 1) AS far FROM pos LEFT JOIN bfs ON bfs.vertex = pos.id GROUP BY 1)
        SELECT chunk_id, width FROM ch WHERE far""",
    "unvisited_anti": f"SELECT vertex AS id FROM ({bfs('geo_tree')}) WHERE dist IS NULL OR dist > 2",
    "compare_levels_outer": f"""SELECT da, db, count(*) AS vertices FROM ({bfs_ctes('geo_tree')} SELECT vertex, dist AS da FROM bfs) FULL JOIN ({bfs_ctes('geo_tree', '20000000')} SELECT vertex, dist AS db FROM bfs) USING (vertex) GROUP BY ALL""",
    "two_hop": f"WITH e AS ({graph_sql('geo_tree')}) SELECT a.src, count(DISTINCT b.dst) AS two_hop FROM e a JOIN e b ON a.dst = b.src WHERE a.src <> b.dst GROUP BY a.src",
    "triangle_count": f"WITH u AS MATERIALIZED (SELECT src, dst FROM ({graph_sql('er')}) WHERE src < dst) SELECT count(*) AS triangles FROM u a JOIN u b ON a.src = b.src AND a.dst < b.dst JOIN u c ON c.src = a.dst AND c.dst = b.dst",
    "product_hash_agg": f"SELECT dst AS row, min(deg) + 1 AS y FROM ({E_SP}) JOIN {D_SP} ON id = src GROUP BY dst",
    "product_sort_agg": f"SELECT src AS row, cast(sum(deg) AS BIGINT) AS y FROM ({E_SP}) JOIN {D_SP} ON id = dst GROUP BY src",
    "neighbour_counts": "SELECT l_suppkey, count(DISTINCT l_partkey) AS parts, count(*) AS lines FROM lineitem GROUP BY 1",
    "level_cube": f"SELECT dist, c_mktsegment, count(*) AS n FROM {SEG} GROUP BY CUBE (dist, c_mktsegment)",
    "level_rollup": f"SELECT dist, c_mktsegment, count(*) AS n FROM {SEG} GROUP BY ROLLUP (dist, c_mktsegment)",
    "level_grouping_sets": f"SELECT dist, c_mktsegment, count(*) AS n FROM {SEG} GROUP BY GROUPING SETS ((dist), (c_mktsegment))",
    "adjacency_arrays": f"SELECT src AS vertex, count(*) AS k, string_agg(cast(dst AS VARCHAR), ',' ORDER BY dst) AS nbrs FROM ({graph_sql('geo_tree')}) GROUP BY src",
    "parent_by_max": f"SELECT dst, max(src) AS largest, min(src) AS least FROM ({E_SP}) GROUP BY dst",
    "degree_percentiles": f"SELECT {', '.join(f'quantile_cont(cast(deg AS DOUBLE), {p}) AS p{int(100 * p)}' for p in (0.25, 0.5, 0.75, 0.99))} FROM {D_SP}",
    "trace_pivot": f"{bfs_ctes()} SELECT dist AS iter, count(*) AS tropical, count(*) AS boolean, count(*) AS real, count(*) AS selmax FROM bfs WHERE dist > 0 GROUP BY dist",
    "level_conditional_counts": f"SELECT count(*) FILTER (dist <= 1) AS near, count(*) FILTER (dist > 1) AS far, count(*) FILTER (vertex % 2 = 0) AS left_side FROM ({bfs()})",
    "degree_tail_regression": f"""WITH {_e('page_links')}, h AS (SELECT deg, count(*) AS cnt FROM deg GROUP BY 1) SELECT round(exp(regr_intercept(ln(cnt / n), ln(deg))), 6) AS alpha, round(-regr_slope(ln(cnt / n), ln(deg)), 6) AS beta FROM h, (SELECT sum(cnt) AS n FROM h)""",
    "positions_ranked": f"SELECT id, cast(row_number() OVER (PARTITION BY id // 256 ORDER BY deg DESC, id) AS INTEGER) AS rn, cast(rank() OVER (PARTITION BY id // 256 ORDER BY deg DESC) AS INTEGER) AS rk, cast(dense_rank() OVER (PARTITION BY id // 256 ORDER BY deg DESC) AS INTEGER) AS dr FROM {D_SP}",
    "static_assignment": f"SELECT id, cast(ntile(4) OVER w AS INTEGER) AS worker, round(percent_rank() OVER w, 9) AS pr, round(cume_dist() OVER w, 9) AS cd FROM {D_SP} WINDOW w AS (PARTITION BY id % 2 ORDER BY deg DESC, id)",
    "event_chain_edges": "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
    "chunk_offsets": f"WITH {_e(DEFAULT)}, {positions(DEFAULT, None)}, c AS (SELECT pos // 8 AS chunk_id, max(deg) AS cl FROM pos GROUP BY 1) SELECT chunk_id, cl, cast(8 * coalesce(sum(cl) OVER (ORDER BY chunk_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS cs FROM c",
    "recent_degree": f"SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY s RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS recent FROM (SELECT event_id, user_id, {EPOCH} AS s FROM events)",
    "last_edge_value": "SELECT DISTINCT user_id, first_value(event_id) OVER w AS first, last_value(event_id) OVER w AS last, nth_value(event_id, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)",
    "global_degree_order": f"SELECT id, deg, row_number() OVER (ORDER BY deg DESC, id) - 1 AS pos FROM {D_SP}",
    "partition_sorted_edges": f"SELECT DISTINCT dst AS vertex FROM ({E_SP})",
    "top_degrees": f"SELECT id, deg FROM {D_SP} ORDER BY deg DESC, id LIMIT 20 OFFSET 5",
    "farthest_per_group": f"SELECT c_mktsegment, vertex, dist, cast(rn AS INTEGER) AS rn FROM (SELECT *, row_number() OVER (PARTITION BY c_mktsegment ORDER BY dist DESC NULLS LAST, vertex) AS rn FROM {SEG}) WHERE rn <= 3",
    "symmetrised_edges": graph_sql("geo_tree"),
    "edge_snapshot_diff": "SELECT l_suppkey, l_partkey FROM lineitem WHERE year(l_shipdate) = 1996 EXCEPT SELECT l_suppkey, l_partkey FROM lineitem WHERE year(l_shipdate) = 1995",
    "edge_snapshot_diff_all": "SELECT l_suppkey, count(*) AS more FROM (SELECT l_suppkey FROM lineitem WHERE year(l_shipdate) = 1996 EXCEPT ALL SELECT l_suppkey FROM lineitem WHERE year(l_shipdate) = 1995) GROUP BY 1",
    "common_neighbours_intersect": f"WITH e AS MATERIALIZED ({E_SP}), t AS (SELECT id, row_number() OVER (ORDER BY deg DESC, id) AS k FROM {D_SP}) SELECT dst FROM e WHERE src = (SELECT id FROM t WHERE k = 1) INTERSECT SELECT dst FROM e WHERE src = (SELECT id FROM t WHERE k = 2)",
    "url_parts": "SELECT page_id, host, string_split(host, '.')[-1] AS top, md5(url) AS digest FROM (SELECT page_id, url, lower(regexp_extract(url, '://([^/?#]*)', 1)) AS host FROM pages)",
    "hourly_vertices": "SELECT date_trunc('hour', ts) AS hour, count(DISTINCT user_id) AS users FROM events GROUP BY 1",
    "bound_math": f"SELECT id, round(log2(deg), 9) AS lg, pow(cast(deg AS DOUBLE), 2.0) AS sq, cast(ceil(deg / 8) AS BIGINT) AS chunks, deg << 2 AS four, greatest(deg, 100) AS top, deg % 8 AS rest FROM {D_SP}",
    "lane_arrays": f"""WITH v AS (SELECT id // 16 AS g, list(deg ORDER BY deg) AS v FROM {D_SP} GROUP BY 1), a AS (SELECT g, list_resize(v, 16, 0) AS a FROM v), p AS (SELECT g, a, list_reverse(a) AS b FROM a)
        SELECT g, cast(sum(least(x, y)) AS BIGINT) AS lo, cast(sum(greatest(x, y)) AS BIGINT) AS hi, cast(sum(x + y) AS BIGINT) AS add, count(*) FILTER (x = y) AS eq, cast(sum(CASE WHEN x = y THEN y ELSE x END) AS BIGINT) AS pick,
          count(*) FILTER (x = 0) AS no, count(*) FILTER (x <> 0) AS yes, any_value(a[1] + a[2]) AS load, any_value(a[1]) AS got FROM (SELECT g, a, unnest(a) AS x, unnest(b) AS y FROM p) GROUP BY g""",
    "slot_maps": "SELECT n_regionkey, cast(slot AS INTEGER) AS slot, n_nationkey AS nation FROM (SELECT *, row_number() OVER (PARTITION BY n_regionkey ORDER BY n_nationkey) - 1 AS slot FROM nation) WHERE slot % 2 = 0",
    "props_edges": "SELECT user_id AS a, cast(json_extract(props, '$.k') AS INTEGER) AS b, count(*) AS n FROM events WHERE json_extract(props, '$.k') IS NOT NULL GROUP BY ALL",
    "knn_edges": """WITH v AS (SELECT vec_id AS id, cast(embedding AS DOUBLE[]) AS v FROM embeddings), n AS (SELECT a.id AS a, b.id AS b FROM v a JOIN v b ON a.id <> b.id QUALIFY row_number() OVER (PARTITION BY a.id ORDER BY list_cosine_similarity(a.v, b.v) DESC, b.id) <= 4)
        SELECT a AS src, b AS dst FROM n UNION SELECT b, a FROM n""",
    "packed_bit_frontier": f"SELECT vertex // 63 AS word, bit_or(cast(1 AS BIGINT) << (vertex % 63)) AS bits, cast(count(*) AS INTEGER) AS n FROM ({bfs()}) WHERE dist = 1 GROUP BY 1",
    "kernel_map": f"WITH {_e(DEFAULT)}, {positions(DEFAULT, None)} SELECT pos // 8 AS chunk_id, max(deg) * 8 AS cells FROM pos GROUP BY 1",
    "lane_udf": f"SELECT id, cast(deg % 2 = 0 AS BIGINT) AS even FROM {D_SP}",
    "lane_merge": f"SELECT id, deg FROM {D_SP}",
    "unpack_chunk": f"WITH {_e('geo_tree')}, {positions('geo_tree', None)} SELECT pos AS row, deg AS k FROM pos",
}
ROOT_USER = "(SELECT min(2 * user_id) FROM events)"
STREAMS = {
    "stream_enrich": "SELECT event_id, user_id AS src, c_nationkey FROM events JOIN customer ON c_custkey = user_id",
    "stream_dedupe": "SELECT DISTINCT user_id AS src, event_type FROM events",
    "stream_coactivity": "WITH p AS (SELECT user_id, ts FROM events WHERE event_type = 'purchase') SELECT DISTINCT x.user_id AS a, y.user_id AS b FROM p x JOIN p y ON x.user_id < y.user_id AND y.ts BETWEEN x.ts - INTERVAL 5 MINUTES AND x.ts + INTERVAL 5 MINUTES",
    "stream_distance": bfs_from("purchase_hour", ROOT_USER),
    "stream_degrees_session": """WITH s AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTES THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
        k AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM s) SELECT min(ts) AS start, max(ts) + INTERVAL 30 MINUTES AS finish, user_id AS src, count(*) AS deg FROM k GROUP BY user_id, k""",
    "stream_degrees_tumbling": "SELECT date_trunc('hour', ts) AS start, date_trunc('hour', ts) + INTERVAL 1 HOUR AS finish, user_id AS src, count(*) AS deg FROM events GROUP BY ALL",
    "stream_degrees_sliding": "SELECT start, start + INTERVAL 1 HOUR AS finish, user_id AS src, count(*) AS deg FROM (SELECT user_id, time_bucket(INTERVAL 15 MINUTES, ts) - to_minutes(15 * k) AS start FROM events, range(4) t(k)) GROUP BY ALL",
}


def weighted_product() -> str:
    """Degrees times summed quantities along the edges of supplier_part."""
    return f"""WITH w AS (SELECT 2 * l_suppkey AS a, 2 * l_partkey + 1 AS b, sum(l_quantity) AS w FROM lineitem GROUP BY l_suppkey, l_partkey), e AS (SELECT a AS row, b AS col, w FROM w UNION ALL SELECT b, a, w FROM w)
        SELECT row AS vertex, round(sum(w * deg), 4) AS y FROM e JOIN {D_SP} ON id = col GROUP BY row"""


def tiled_imbalance(name: str, c: int, tile: int, workers: int) -> str:
    """Tiles of `tile` columns in order of (chunk, tile), equal counts a worker."""
    return f"""WITH {_e(name)}, {positions(name, None)}, ch AS (SELECT pos // {c} AS ch, max(deg) AS w FROM pos GROUP BY 1), ti AS (SELECT ch, t, least(w - t * {tile}, {tile}) * {c} AS slots FROM ch, range(1000) r(t) WHERE t * {tile} < w),
        k AS (SELECT slots, (row_number() OVER (ORDER BY ch, t) - 1) * {workers} // (SELECT count(*) FROM ti) AS worker FROM ti), o AS (SELECT worker, sum(slots) AS slots FROM k GROUP BY 1)
        SELECT {workers} AS workers, 'tiled' AS schedule, round(max(slots) * {workers} / sum(slots), 6) AS imbalance FROM o"""


def work_table(name: str, c: int, key_bits: int = 32) -> str:
    forms = {
        "queue": "n + m", "bag": "n + m", "direction": "d * n + d * m", "textbook_dense": "d * n * n", "csr": "d * n + d * m", "sparse_sort": "n + m * log2(greatest(m, 2))",
        "sparse_radix": f"n + {key_bits} * m", "sparse_hash": "n + m", "slices": f"d * n + d * m + d * {c} * top",
    }
    size = f"{bfs_ctes(name)}, s AS (SELECT count(*) AS n, cast(sum(deg) AS BIGINT) // 2 AS m, max(deg) AS top, (SELECT max(dist) FROM bfs) AS d FROM deg)"
    return size + " " + " UNION ALL ".join(f"SELECT '{k}' AS method, cast({v} AS DOUBLE) AS work FROM s" for k, v in forms.items())


def pagerank(name: str, rounds: int, damping: float = 0.85) -> str:
    steps = ["r0 AS (SELECT id, 1.0::DOUBLE / (SELECT count(*) FROM deg) AS r FROM deg)"]
    for k in range(rounds):
        steps.append(f"r{k + 1} AS MATERIALIZED (SELECT d.id, (1 - {damping}) / (SELECT count(*) FROM deg) + {damping} * coalesce(sum(p.r / q.deg), 0) AS r FROM deg d LEFT JOIN e ON e.dst = d.id LEFT JOIN r{k} p ON p.id = e.src LEFT JOIN deg q ON q.id = e.src GROUP BY d.id)")
    return f"WITH {_e(name)}, {', '.join(steps)} SELECT id AS vertex, round(r, 12) AS rank FROM r{rounds}"


def betweenness(name: str, depth: int) -> str:
    """Dependencies of a root, from the deepest level up; depth: an upper bound of the levels."""
    steps = [f"x{depth} AS MATERIALIZED (SELECT vertex, 0.0::DOUBLE AS delta FROM bfs WHERE dist = {depth})"]
    for k in range(depth - 1, -1, -1):
        steps.append(f"x{k} AS MATERIALIZED (SELECT a.vertex, coalesce(sum(a.paths / b.paths * (1 + x.delta)), 0) AS delta FROM bfs a LEFT JOIN (e JOIN bfs b ON b.vertex = e.dst AND b.dist = {k + 1} JOIN x{k + 1} x ON x.vertex = b.vertex) ON e.src = a.vertex WHERE a.dist = {k} GROUP BY a.vertex)")
    every = " UNION ALL ".join(f"SELECT * FROM x{k}" for k in range(depth + 1))
    return f"{bfs_ctes(name)}, {', '.join(steps)}, y AS ({every}) SELECT vertex, round(delta, 9) AS dependency FROM y"


# Vertices of the generated graphs, which are the same at every scale.
GENERATED = {"kron": 1580, "er": 2048}


def _row(w: str, g: str, variant: str, c: int, sigma: str, it: str, metric: str, value: str, source: str) -> str:
    return f"SELECT '{w}' AS workload, '{g}' AS graph, '{variant}' AS variant, {c} AS c, cast({sigma} AS BIGINT) AS sigma, cast({it} AS INTEGER) AS iter, '{metric}' AS metric, cast({value} AS DOUBLE) AS value FROM ({source})"


def _scope(name: str, sigma: int | None) -> str:
    return str(sigma) if sigma else f"(SELECT count(DISTINCT src) FROM ({graph_sql(name)}))"


def traced(w: str, g: str, variant: str, c: int, sigma: int | None, skip: bool) -> list[str]:
    return [_row(w, g, variant, c, _scope(g, sigma), "iter", m, m, work(g, c, sigma, skip)) for m in ("frontier", "slots", "skipped")]


def swept(w: str, g: str, variant: str, c: int, scopes: tuple | None = None) -> list[str]:
    from graphslices.layout import sigma_ladder

    if scopes:
        return [_row(w, g, variant, c, _scope(g, s), "NULL", "pad_slots", "pad_slots", padding(g, c, [s])) for s in scopes]
    n = GENERATED[g]
    return [_row(w, g, variant, c, str(s), "NULL", "pad_slots", "pad_slots", padding(g, c, [None if s >= n else s])) for s in sigma_ladder(n, c)]


# What the tables have for the generated graphs: links of pages are skewed and fall apart into components as the Kronecker graph's edges, users and hours of events meet at random and have nearly equal degrees.
GIVEN = {"kron": "page_links", "er": "user_hour"}
SCOPES = (1, 8, 64, 512, 4096, None)


def _counted() -> dict[str, tuple[dict, str]]:
    """Workload -> (options of experiments.counted, statement): what does not depend on the clock."""
    from graphslices.layout import default_sigma
    from graphslices.semiring import SEMIRINGS

    out: dict[str, tuple[dict, list[str]]] = {}
    out["W-01"] = ({"graphs": ("kron",), "metrics": ("pad_slots",)}, swept("W-01", "kron", "static", 8))
    for w, g, variant, c in (("W-02", "kron", "dynamic", 8), ("W-03", "er", "dynamic", 8), ("W-08", "kron", "dynamic", 32), ("W-09", "er", "dynamic", 32)):
        out[w] = ({"given": GIVEN, "scopes": SCOPES, "metrics": ("pad_slots",)}, swept(w, GIVEN[g], variant, c, SCOPES))
    out["W-04"] = ({"graphs": ("kron", "er")}, [q for g in ("kron", "er") for s in (1, default_sigma(GENERATED[g], 8), None) for k in (True, False) for q in traced("W-04", g, "skip" if k else "plain", 8, s, k)])
    reached = lambda g: f"SELECT count(*) AS k FROM ({bfs(g)}) WHERE dist IS NOT NULL"
    out["W-05"] = ({}, [q for g in ("kron", "order_part") for s in SEMIRINGS.values() for q in (_row("W-05", g, s.name, 8, "NULL", "NULL", "reached", "k", reached(g)), _row("W-05", g, s.name, 8, "NULL", "NULL", "post_ops", str(s.post_ops), "SELECT 1"))])
    cells = lambda g, s: f"SELECT * FROM ({storage(g, 8, [s])})"
    skewed = GIVEN["kron"]
    out["W-06"] = ({"given": GIVEN}, [_row("W-06", skewed, f"{s.name} {k}", 8, _scope(skewed, sigma), "NULL", "cells", "cells", f"SELECT cells FROM ({cells(skewed, sigma)}) WHERE layout = '{k}'") for sigma in (16, None) for s in SEMIRINGS.values() for k in ("valued", "pattern")])
    family = []
    for label, g in (("community", "user_hour"), ("small", "geo_tree"), ("hub-heavy", "supplier_part"), ("road", "event_chain"), ("short paths", "conv_chain"), ("clustered", "shared_lines")):
        ratio = f"SELECT round(cast((SELECT sum(slots) FROM ({work(g, 8, None, True)})) AS DOUBLE) / (SELECT sum(slots) FROM ({work(g, 8, None, False)})), 6) AS r"
        family.append(_row("W-07", g, label, 8, "NULL", "NULL", "work_ratio", "r", ratio))
        family.append(_row("W-07", g, label, 8, "NULL", "NULL", "levels", "r", f"SELECT max(dist) AS r FROM ({bfs(g)})"))
        for metric, other in (("cells_to_valued", "valued"), ("cells_to_al", "al")):
            family.append(_row("W-07", g, label, 8, "NULL", "NULL", metric, "r", f"SELECT round(max(cells) FILTER (layout = 'pattern') / max(cells) FILTER (layout = '{other}'), 6) AS r FROM ({storage(g, 8, [None])})"))
    out["W-07"] = ({"graphs": ("user_hour", "geo_tree", "supplier_part", "event_chain", "conv_chain", "shared_lines")}, family)
    out["W-10"] = ({"given": GIVEN}, [q for s in SEMIRINGS for q in traced("W-10", skewed, s, 32, 1024, True)])
    out["W-12"] = ({"given": GIVEN, "metrics": ("frontier", "slots", "skipped")}, [q for v in ("whole", "tiled") for q in traced("W-12", skewed, v, 32, 1024, True)])
    some = ("kron", "er", "supplier_part", "order_part", "geo_tree", "event_chain")
    out["W-17"] = ({"graphs_run": tuple(GIVEN.values()), "scopes": SCOPES}, [])
    for g in GIVEN.values():
        for c in (8, 32):
            for s in SCOPES:
                out["W-17"][1].append(f"SELECT 'W-17' AS workload, '{g}' AS graph, layout AS variant, c, cast({_scope(g, s)} AS BIGINT) AS sigma, cast(NULL AS INTEGER) AS iter, 'cells' AS metric, cast(cells AS DOUBLE) AS value FROM ({storage(g, c, [s])})")
    out["W-19"] = ({"given": GIVEN}, traced("W-19", skewed, "tropical, skip, tiles", 8, None, True))
    bound = []
    for g in some:
        levels = f"SELECT sum(slots) AS work, max(iter) AS d FROM ({work(g, 8, None, False)})"
        size = f"SELECT count(*) AS n, sum(deg) AS nnz, max(deg) AS top FROM (SELECT src, count(*) AS deg FROM ({graph_sql(g)}) GROUP BY 1)"
        bound.append(_row("W-20", g, "measured", 8, "NULL", "NULL", "work", "work", levels))
        bound.append(_row("W-20", g, "general", 8, "NULL", "NULL", "bound", "d * (n + nnz + 8 * top)", f"SELECT * FROM ({levels}), ({size})"))
    out["W-20"] = ({"graphs": some, "graphs_run": some, "variants": ("measured", "general")}, bound)
    return {w: (o, " UNION ALL ".join(q)) for w, (o, q) in out.items()}


COUNTED = _counted()


__all__ = ["DEFAULT", "RELATIONAL", "STREAMS", "bfs", "bfs_ctes", "graph_sql", "padding", "parents", "positions", "storage", "weighted_product", "work"]
