"""Costs as data: storage in cells, padding, work, balance, bounds, amortisation, exactness. Each measure is a DataFrame."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphslices.bfs.dense import PIECES, BfsResult, bfs_dense
from graphslices.layout import Layout, sorted_positions
from graphslices.session import cut

LAYOUTS = ("al", "csr", "valued", "pattern")


def _row(spark: SparkSession, **values) -> DataFrame:
    """One row of doubles, longs and strings."""
    kinds = {float: "double", int: "long", str: "string", bool: "boolean"}
    return spark.createDataFrame([tuple(values.values())], ", ".join(f"{k} {kinds[type(v)]}" for k, v in values.items()))


# -- storage -------------------------------------------------------------------------------------------------------------------------------


def cells_formula(n: int, nnz: int, pad: int, c: int) -> dict[str, float]:
    """Cells of each layout in closed form, nnz being twice the edges: the printed forms, with 2n/C for the chunk directory and one P for the padding."""
    return {"al": nnz + n, "csr": 2 * nnz + n, "valued": 2 * nnz + 2 * n / c + pad, "pattern": nnz + 2 * n / c + pad}


def cells_exact(n: int, nnz: int, pad: int, c: int) -> dict[str, int]:
    """The same counted exactly: a padded slot of valued slices lies in both arrays, and the directory has two cells for each of ceil(n / C) chunks."""
    d = 2 * -(-n // c)
    return {"al": nnz + n, "csr": 2 * nnz + n, "valued": 2 * (nnz + pad) + d, "pattern": nnz + pad + d}


def padding_by_sigma(deg: DataFrame, c: int, sigmas: list[int | None]) -> DataFrame:
    """(c, sigma, n, nnz, slots, pad_slots) for each scope, from degrees alone: no slice is built. Scope 0 stands for all rows."""
    out = None
    for sigma in sigmas:
        pos = sorted_positions(deg, sigma)
        chunks = pos.groupBy(F.floor(F.col("pos") / c)).agg(F.max("deg").alias("w"), F.sum("deg").alias("s"), F.count("*").alias("k"))
        one = chunks.agg(F.sum("k").alias("n"), F.sum("s").alias("nnz"), (F.sum("w") * c).alias("slots"))
        one = one.select(F.lit(c).alias("c"), F.lit(sigma or 0).cast("long").alias("sigma"), "n", "nnz", "slots", (F.col("slots") - F.col("nnz")).alias("pad_slots"))
        out = one if out is None else out.unionByName(one)
    return out


def storage_report(padding: DataFrame) -> DataFrame:
    """(c, sigma, layout, cells, cells_formula) for all four layouts of each row of padding_by_sigma."""
    n, nnz, pad, c = (F.col(x) for x in ("n", "nnz", "pad_slots", "c"))
    chunks = F.ceil(n / c)
    exact = {"al": nnz + n, "csr": 2 * nnz + n, "valued": 2 * (nnz + pad) + 2 * chunks, "pattern": nnz + pad + 2 * chunks}
    formula = {"al": nnz + n, "csr": 2 * nnz + n, "valued": 2 * nnz + 2 * n / c + pad, "pattern": nnz + 2 * n / c + pad}
    rows = F.array(*[F.struct(F.lit(k).alias("layout"), exact[k].cast("long").alias("cells"), F.round(formula[k].cast("double"), 6).alias("cells_formula")) for k in LAYOUTS])
    return padding.select("c", "sigma", F.explode(rows).alias("r")).select("c", "sigma", "r.*")


def storage_cells(layout: Layout) -> DataFrame:
    """(layout, cells_measured): cells of the arrays that are there, and the directory's."""
    size = F.size("col").cast("long") + (F.size("val") if layout.valued else F.lit(0))
    total = layout.slices.agg(F.coalesce(F.sum(size), F.lit(0)).alias("s"))
    return total.select(F.lit("valued" if layout.valued else "pattern").alias("layout"), (F.col("s") + 2 * layout.chunks).alias("cells_measured"))


def layout_bytes(spark: SparkSession, path: str) -> DataFrame:
    """(file, bytes) of the files under a path, of any store Spark reads."""
    return spark.read.format("binaryFile").option("recursiveFileLookup", "true").option("pathGlobFilter", "*.parquet").load(path).select(F.col("path").alias("file"), F.col("length").alias("bytes"))


def padding_slots(layout: Layout) -> DataFrame:
    return product_slots(layout).select((F.col("slots") - layout.nnz).alias("pad_slots"))


def padding_bound(summary: DataFrame, c: int) -> DataFrame:
    """(bound, least_slots): padding at full scope is at most C times the largest degree, slots at least the larger of that (if there are C rows) and nnz."""
    top = F.col("max_deg") * c
    return summary.select(top.alias("bound"), F.greatest(F.col("nnz"), F.when(F.col("n") >= c, top).otherwise(F.lit(0))).alias("least_slots"))


def layout_ratio(report: DataFrame) -> DataFrame:
    """(c, sigma, to_valued, to_al, to_csr): cells of pattern slices over those of the others."""
    wide = report.groupBy("c", "sigma").pivot("layout", list(LAYOUTS)).agg(F.first("cells"))
    return wide.select("c", "sigma", *[F.round(F.col("pattern") / F.col(k), 6).alias(f"to_{k}") for k in ("valued", "al", "csr")])


def beats_adjacency_list(padding: DataFrame) -> DataFrame:
    """(c, sigma, share, limit, beats): padding a row against 1 - 2/C."""
    limit = 1 - 2 / F.col("c")
    share = F.col("pad_slots") / F.col("n")
    return padding.select("c", "sigma", F.round(share, 6).alias("share"), F.round(limit, 6).alias("limit"), (share < limit).alias("beats"))


# -- work ----------------------------------------------------------------------------------------------------------------------------------


def product_slots(layout: Layout) -> DataFrame:
    return layout.slices.agg(F.coalesce(F.sum(F.col("width").cast("long") * layout.c), F.lit(0)).cast("long").alias("slots"))


def trace_work(result: BfsResult, layout: Layout) -> DataFrame:
    """A trace with the work of the skip tests and the share of skipped chunks."""
    return result.trace.select(
        "iter", "frontier", "slots", "skipped", F.lit(layout.c * layout.chunks).cast("long").alias("test_work"), F.round(F.col("skipped") / layout.chunks, 6).alias("skipped_share")
    )


def total_work(skip: BfsResult, plain: BfsResult) -> DataFrame:
    a = skip.trace.agg(F.sum("slots").alias("with_skip"))
    return a.crossJoin(plain.trace.agg(F.sum("slots").alias("without"))).withColumn("ratio", F.round(F.col("with_skip") / F.col("without"), 6))


def work_bound_general(n: int, nnz: int, c: int, max_deg: int, d: int) -> int:
    return d * (n + nnz + c * max_deg)


def work_bound_er(n: int, p: float, c: int, d: int) -> float:
    """With largest degree of order log n while n p is at most that, and of order n p beyond."""
    return d * (n + n * n * p + c * max(math.log(max(n, 2)), n * p))


def largest_degree_powerlaw(n: int, alpha: float, beta: float) -> float:
    if beta <= 1:
        raise ValueError("beta must exceed 1")
    try:
        return (alpha * n * math.log(max(n, 2))) ** (1 / (beta - 1))
    except OverflowError:  # a law close to 1 / degree bounds nothing that a double holds
        return math.inf


def work_bound_powerlaw(n: int, nnz: int, c: int, d: int, alpha: float, beta: float) -> float:
    return d * (n + nnz + c * largest_degree_powerlaw(n, alpha, beta))


def fit_power_law(hist: DataFrame) -> DataFrame:
    """(alpha, beta) of cnt / n = alpha * deg ** -beta by least squares on logarithms."""
    n = hist.agg(F.sum("cnt").alias("n"))
    logs = hist.where("deg > 0").crossJoin(n).select(F.log("deg").alias("x"), F.log(F.col("cnt") / F.col("n")).alias("y"))
    return logs.agg(F.round(F.exp(F.regr_intercept("y", "x")), 6).alias("alpha"), F.round(-F.regr_slope("y", "x"), 6).alias("beta"))


def work_table(spark: SparkSession, n: int, m: int, d: int, c: int, max_deg: int, key_bits: int = 32) -> DataFrame:
    """(method, work): the asymptotic work of every traversal, constants left out."""
    rows = [
        ("queue", n + m), ("bag", n + m), ("direction", d * n + d * m), ("textbook_dense", d * n * n), ("csr", d * n + d * m),
        ("sparse_sort", n + m * math.log2(max(m, 2))), ("sparse_radix", n + key_bits * m), ("sparse_hash", n + m), ("slices", d * n + d * m + d * c * max_deg),
    ]
    return spark.createDataFrame([(k, float(v)) for k, v in rows], "method string, work double")


# -- time and balance ----------------------------------------------------------------------------------------------------------------------


def drain(df: DataFrame) -> None:
    """Runs a plan and drops its rows."""
    df.write.format("noop").mode("overwrite").save()


def timed(spark: SparkSession, run: Callable[[], object], repeats: int = 1, name: str = "run") -> DataFrame:
    """(name, repeat, seconds)."""
    rows = []
    for k in range(repeats):
        began = time.time()
        got = run()
        if isinstance(got, DataFrame):
            drain(got)
        rows.append((name, k, time.time() - began))
    return spark.createDataFrame(rows, "name string, repeat int, seconds double")


def speedup(base: DataFrame, other: DataFrame) -> DataFrame:
    """(ratio, percent) of mean seconds."""
    a, b = base.agg(F.avg("seconds").alias("a")), other.agg(F.avg("seconds").alias("b"))
    return a.crossJoin(b).select((F.col("a") / F.col("b")).alias("ratio"), (100 * (F.col("a") / F.col("b") - 1)).alias("percent"))


def amortization(spark: SparkSession, t_pre: float, t_run: float, runs: list[int]) -> DataFrame:
    """(runs, share): preprocessing's share of all time, for numbers of runs."""
    return spark.createDataFrame([(r, round(t_pre / (t_pre + r * t_run), 6)) for r in runs], "runs int, share double")


def imbalance(layout: Layout, workers: int, schedule: str = "static") -> DataFrame:
    """(workers, schedule, imbalance): largest over mean slots of a worker. static: equal counts of chunks in order; tiled: equal counts of tiles in order; dynamic: PIECES pieces a worker, dealt as bfs_dense deals them, each taken in turn by the worker that is free first."""
    tiles = layout.slices.select("chunk_id", "tile_id", (F.col("width").cast("long") * layout.c).alias("slots"))
    if schedule == "dynamic":
        loads = [0] * workers
        pieces = tiles.groupBy((F.col("chunk_id") % (PIECES * workers)).alias("piece")).agg(F.sum("slots").alias("slots")).orderBy("piece").collect()  # PIECES rows a worker
        for r in pieces:
            loads[loads.index(min(loads))] += r.slots
        return tiles.sparkSession.createDataFrame([(workers, schedule, round(max(loads) * workers / max(1, sum(loads)), 6))], "workers int, schedule string, imbalance double")
    if schedule == "static":
        owned = tiles.withColumn("worker", F.floor(F.col("chunk_id") * workers / layout.chunks))
    else:
        from graphslices.edges import global_rank

        total = tiles.count()
        owned = global_rank(tiles, F.asc("chunk_id"), F.asc("tile_id")).withColumn("worker", F.floor(F.col("pos") * workers / total))
    load = owned.groupBy("worker").agg(F.sum("slots").alias("slots"))
    return load.agg(F.max("slots").alias("top"), F.sum("slots").alias("all")).select(
        F.lit(workers).alias("workers"), F.lit(schedule).alias("schedule"), F.round(F.col("top") * workers / F.col("all"), 6).alias("imbalance")
    )


def recovery_overhead(layout: Layout, edges: DataFrame, root: int, semiring: str = "tropical") -> DataFrame:
    """(semiring, seconds_plain, seconds_recovery, edges_read)."""
    spark = edges.sparkSession
    plain = timed(spark, lambda: bfs_dense(layout, root, semiring).df).first().seconds
    more = timed(spark, lambda: bfs_dense(layout, root, semiring, parents="recover", edges=edges).df).first().seconds
    return _row(spark, semiring=semiring, seconds_plain=plain, seconds_recovery=more, edges_read=layout.nnz)


def scaling(spark: SparkSession, prepare: Callable[[int, int], Callable[[], object]], workers: list[int], mode: str = "strong", size: int = 1, repeats: int = 3) -> DataFrame:
    """(mode, workers, size, seconds): one size for all in strong scaling, size times workers in weak scaling. prepare(workers, size) builds what a run needs, untimed; then the run is warmed up, and the median of its repeats counts."""
    rows = []
    for w in workers:
        k, took = size if mode == "strong" else size * w, []
        run = prepare(w, k)
        run()
        for _ in range(repeats):
            began = time.time()
            run()
            took.append(time.time() - began)
        rows.append((mode, w, k, sorted(took)[len(took) // 2]))
    return spark.createDataFrame(rows, "mode string, workers int, size int, seconds double")


def bytes_avoided(layout: Layout, result: BfsResult) -> DataFrame:
    """(iter, col_bytes, val_bytes, skipped_bytes): what each level reads, what it would read besides if values were kept, and what skipping leaves out of the two, at eight bytes a cell."""
    all_ = product_slots(layout).select(F.col("slots").alias("all"))
    return result.trace.crossJoin(F.broadcast(all_)).select("iter", (F.col("slots") * 8).alias("col_bytes"), (F.col("slots") * 8).alias("val_bytes"), ((F.col("all") - F.col("slots")) * 16).alias("skipped_bytes"))


def edge_rate(result: BfsResult, edges: DataFrame) -> DataFrame:
    """(edges_reached, ms, edges_per_second)."""
    reached = result.df.where("dist IS NOT NULL").select(F.col("vertex").alias("src"))
    m = edges.join(reached, "src", "left_semi").agg((F.count("*") / 2).cast("long").alias("edges_reached"))
    return m.crossJoin(result.trace.agg(F.sum("ms").alias("ms"))).withColumn("edges_per_second", F.col("edges_reached") * 1000.0 / F.greatest("ms", F.lit(1)))


# -- exactness -----------------------------------------------------------------------------------------------------------------------------


def diff_results(a: DataFrame, b: DataFrame) -> DataFrame:
    """Vertices with different distances, or in one result only."""
    x, y = a.select("vertex", F.col("dist").alias("dist_a"), F.lit(True).alias("in_a")), b.select("vertex", F.col("dist").alias("dist_b"), F.lit(True).alias("in_b"))
    both = x.join(y, "vertex", "full_outer")
    return both.where(F.col("in_a").isNull() | F.col("in_b").isNull() | ~F.equal_null("dist_a", "dist_b")).select("vertex", "dist_a", "dist_b")


def invalid_parents(edges: DataFrame, result: DataFrame) -> DataFrame:
    """Vertices whose parent is no neighbour one level nearer (the root's is itself, an unreachable vertex has none)."""
    d = result.select("vertex", "dist", "parent")
    up = d.select(F.col("vertex").alias("parent"), F.col("dist").alias("parent_dist"))
    known = d.join(up, "parent", "left").join(edges.select(F.col("src").alias("vertex"), F.col("dst").alias("parent"), F.lit(True).alias("edge")), ["vertex", "parent"], "left")
    root = (F.col("dist") == 0) & F.equal_null("parent", "vertex")
    none = F.col("dist").isNull() & F.col("parent").isNull()
    fine = F.coalesce((F.col("parent_dist") == F.col("dist") - 1) & F.col("edge"), F.lit(False))
    return known.where(~(F.coalesce(root, F.lit(False)) | none | fine)).select("vertex", "dist", "parent")
