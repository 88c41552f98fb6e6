"""Baselines: traversals by queues, bags, direction inversion, sparse vectors, CSR and dense products, over plain edges.

A level is one job, and frontiers are cut by a reliable checkpoint. Edges go both ways here, so a neighbour of a level lies in it, in the one before or in the next: what is compared with are two levels, however deep the graph is.
With symmetric=False all levels so far are, merged into one table every MERGED levels.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphslices import product
from graphslices.semiring import SEMIRINGS
from graphslices.session import cut


MERGED = 16


def _start(edges: DataFrame, root: int) -> DataFrame:
    return edges.sparkSession.createDataFrame([(root, 0)], "vertex long, dist int")


def _finish(edges: DataFrame, levels: list[DataFrame], vertices: DataFrame | None) -> DataFrame:
    """(vertex, dist), unreachable ones with NULL."""
    from graphslices.edges import vertex_set

    found = reduce(DataFrame.unionByName, levels)
    ids = vertex_set(edges, vertices).select(F.col("id").alias("vertex"))
    return ids.join(found, "vertex", "left").select("vertex", "dist")


def _levels(edges: DataFrame, root: int, step, vertices: DataFrame | None, max_iter: int | None, symmetric: bool = True, whole: bool = False) -> DataFrame:
    """step(frontier, visited, level) gives the next frontier (vertex). whole: the step needs all visited vertices."""
    levels, merged, k = [cut(_start(edges, root))], [], 0
    while max_iter is None or k < max_iter:
        k += 1
        if symmetric and not whole:
            visited = reduce(DataFrame.unionByName, levels[-2:])
        else:
            if len(levels) - len(merged) * MERGED > MERGED:
                merged.append(cut(reduce(DataFrame.unionByName, levels[len(merged) * MERGED : (len(merged) + 1) * MERGED])))
            visited = reduce(DataFrame.unionByName, merged + levels[len(merged) * MERGED :])
        nxt = cut(step(levels[-1].select("vertex"), visited, k).select("vertex", F.lit(k).alias("dist")))
        if nxt.isEmpty():
            break
        levels.append(nxt)
    return _finish(edges, levels, vertices)


def _neighbours(edges: DataFrame, frontier: DataFrame) -> DataFrame:
    return edges.join(frontier.withColumnRenamed("vertex", "src"), "src").select(F.col("dst").alias("vertex"))


def bfs_queue(edges: DataFrame, root: int, precheck: bool = True, vertices: DataFrame | None = None, max_iter: int | None = None, symmetric: bool = True) -> DataFrame:
    """The queue: neighbours of the frontier that have not been visited. precheck tests that before neighbours are gathered by target (the tuned form), else afterwards."""

    def step(frontier: DataFrame, visited: DataFrame, k: int) -> DataFrame:
        near = _neighbours(edges, frontier)
        seen = visited.select("vertex")
        return near.join(seen, "vertex", "left_anti").distinct() if precheck else near.distinct().join(seen, "vertex", "left_anti")

    return _levels(edges, root, step, vertices, max_iter, symmetric)


def bfs_bag(edges: DataFrame, root: int, bags: int = 8, vertices: DataFrame | None = None) -> DataFrame:
    """The frontier is a multiset in bags. A bag takes a vertex once, but does not ask the other bags: who enters two of them is expanded twice, and becomes one when it is put among the visited."""
    levels, k = [cut(_start(edges, root))], 0
    bag = levels[0].select("vertex")
    while True:
        k += 1
        near = edges.join(bag.withColumnRenamed("vertex", "src"), "src").select(F.col("dst").alias("vertex"), F.pmod(F.xxhash64("src"), F.lit(bags)).cast("int").alias("bag"))
        seen = reduce(DataFrame.unionByName, levels[-2:]).select("vertex")
        full = cut(near.join(seen, "vertex", "left_anti").dropDuplicates(["bag", "vertex"]))
        if full.isEmpty():
            return _finish(edges, levels, vertices)
        levels.append(cut(full.select("vertex").distinct().select("vertex", F.lit(k).alias("dist"))))
        bag = full.select("vertex")


def bfs_direction(edges: DataFrame, root: int, alpha: float = 14.0, beta: float = 24.0, vertices: DataFrame | None = None) -> DataFrame:
    """Top-down steps, and bottom-up ones while the frontier's edges outnumber 1/alpha of the unexplored and the frontier 1/beta of all vertices."""
    from graphslices.edges import degrees, vertex_set

    ids = cut(vertex_set(edges, vertices).select(F.col("id").alias("vertex")))
    deg = cut(degrees(edges).withColumnRenamed("id", "vertex"))
    n, nnz = ids.count(), deg.agg(F.coalesce(F.sum("deg"), F.lit(0))).first()[0]
    state = {"up": False, "explored": 0}

    def step(frontier: DataFrame, visited: DataFrame, k: int) -> DataFrame:
        size, work = frontier.join(deg, "vertex", "left").agg(F.count("*"), F.coalesce(F.sum("deg"), F.lit(0))).first()
        state["explored"] += work
        if not state["up"]:
            state["up"] = work > (nnz - state["explored"]) / alpha
        elif size < n / beta:
            state["up"] = False
        if state["up"]:
            left = ids.join(visited.select("vertex"), "vertex", "left_anti")
            back = edges.join(left.withColumnRenamed("vertex", "dst"), "dst", "left_semi")
            return back.join(frontier.withColumnRenamed("vertex", "src"), "src", "left_semi").select(F.col("dst").alias("vertex")).distinct()
        return _neighbours(edges, frontier).join(visited.select("vertex"), "vertex", "left_anti").distinct()

    return _levels(edges, root, step, vertices, None, whole=True)


def sort_dedupe(df: DataFrame) -> DataFrame:
    """Distinct vertices by sorting and comparing neighbours in the order."""
    placed = df.repartition("vertex").sortWithinPartitions("vertex").withColumn("p", F.spark_partition_id())
    before = F.lag("vertex").over(Window.partitionBy("p").orderBy("vertex"))
    return placed.withColumn("before", before).where(F.col("before").isNull() | (F.col("before") != F.col("vertex"))).select("vertex")


def radix_dedupe(df: DataFrame, bits: int = 8) -> DataFrame:
    """Distinct vertices by a radix sort, the lowest digit first: a pass counts the digits, adds up the counts before each and puts a row behind those of its digit that stood before it. Then equal neighbours are one."""
    top = df.agg(F.coalesce(F.max("vertex"), F.lit(0))).first()[0]
    out = df.select("vertex", F.monotonically_increasing_id().alias("pos"))
    for p in range(max(1, -(-int(top).bit_length() // bits))):
        placed = out.withColumn("digit", F.shiftright("vertex", p * bits).bitwiseAND(F.lit((1 << bits) - 1)))
        counts = placed.groupBy("digit").agg(F.count("*").alias("k"))  # a row a digit
        before = F.coalesce(F.sum("k").over(Window.orderBy("digit").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        own = F.row_number().over(Window.partitionBy("digit").orderBy("pos")) - 1
        out = cut(placed.withColumn("own", own).join(F.broadcast(counts.select("digit", before.alias("base"))), "digit").select("vertex", "digit", (F.col("own") + F.col("base")).alias("pos")))
    last = F.lag("vertex").over(Window.partitionBy("digit").orderBy("pos"))
    return out.withColumn("before", last).where(F.col("before").isNull() | (F.col("before") != F.col("vertex"))).select("vertex")


DEDUPE = {"sort": sort_dedupe, "radix": radix_dedupe, "hash": lambda df: df.distinct()}


def bfs_sparse(edges: DataFrame, root: int, dedupe: str = "hash", vertices: DataFrame | None = None) -> DataFrame:
    """Sparse-vector products: the frontier's neighbours, made distinct by sorting, by radix passes or by hashing."""

    def step(frontier: DataFrame, visited: DataFrame, k: int) -> DataFrame:
        return DEDUPE[dedupe](_neighbours(edges, frontier)).join(visited.select("vertex"), "vertex", "left_anti")

    return _levels(edges, root, step, vertices, None)


def bfs_csr(csr: DataFrame, root: int, semiring: str = "boolean", unrolled: int | None = None) -> DataFrame:
    """Dense products over CSR: every row is read at every level. csr: (vertex, nbrs, val) of both directions."""
    s = SEMIRINGS[semiring]
    state = cut(csr.select("vertex", F.when(F.col("vertex") == root, 0).alias("dist")))
    k = 0
    while True:
        k += 1
        one = {"tropical": F.col("dist"), "selmax": F.col("vertex") + 1}.get(s.name, F.lit(1))
        vector = state.where("dist IS NOT NULL" if s.name in ("tropical", "selmax") else F.col("dist") == k - 1).select(F.col("vertex").alias("pos"), one.cast(s.sql_type).alias("x"))
        y = product.mv_csr_unrolled(csr, vector, s, unrolled) if unrolled else product.mv_csr(csr, vector, s)
        new = F.col("dist").isNull() & F.col("y").isNotNull()
        state = cut(state.join(y.withColumnRenamed("row", "vertex"), "vertex", "left").select("vertex", F.when(new, k).otherwise(F.col("dist")).alias("dist")))
        if state.where(F.col("dist") == k).isEmpty():
            return state


def bfs_textbook_dense(edges: DataFrame, root: int, vertices: DataFrame | None = None, max_iter: int | None = None) -> DataFrame:
    """Products over all n * n cells at every level, a cell being a bit."""
    from graphslices.edges import global_rank, vertex_set

    ids = cut(global_rank(vertex_set(edges, vertices), F.asc("id")))
    n, matrix = ids.count(), product.dense_bits(edges, ids)

    def step(frontier: DataFrame, visited: DataFrame, k: int) -> DataFrame:
        y = product.mv_dense_bits(matrix, frontier.join(ids, F.col("vertex") == F.col("id")).select("pos"), n)
        return y.withColumnRenamed("row", "vertex").join(visited.select("vertex"), "vertex", "left_anti")

    return _levels(edges, root, step, vertices, max_iter)


def bfs_recursive_sql(edges: DataFrame, root: int, depth: int) -> DataFrame:
    """Shortest hops by a recursive statement up to a depth: the plain relational reference. A walk does not come back to a vertex it has passed, as no shortest one does; walks that meet elsewhere are all kept."""
    text = """WITH RECURSIVE walk(vertex, dist, path) MAX RECURSION LEVEL {levels} AS (
        SELECT CAST({root} AS BIGINT), 0, array(CAST({root} AS BIGINT)) UNION ALL
        SELECT e.dst, w.dist + 1, concat(w.path, array(e.dst)) FROM walk w JOIN {edges} e ON e.src = w.vertex WHERE w.dist < {depth} AND NOT array_contains(w.path, e.dst))
        SELECT vertex, min(dist) AS dist FROM walk GROUP BY vertex"""
    spark, limit = edges.sparkSession, "spark.sql.cteRecursionRowLimit"
    before = spark.conf.get(limit)
    spark.conf.set(limit, "-1")  # a million rows by default, fewer than a large table's vertices
    try:
        return cut(spark.sql(text, edges=edges, root=root, depth=depth, levels=depth + 2))
    finally:
        spark.conf.set(limit, before)
