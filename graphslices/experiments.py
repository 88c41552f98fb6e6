"""The experiment workloads on the given tables' graphs. run(spark, sf_dir, id, **overrides) gives (workload, graph, variant, c, sigma, iter, metric, value)."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphslices import catalog, cost, generate, layout as L, product
from graphslices.bfs import bfs_dense, bfs_queue
from graphslices.edges import degree_histogram, degree_summary, degrees, pick_root
from graphslices.semiring import REAL, SEMIRINGS
from graphslices.session import cut, stored

SCHEMA = "workload string, graph string, variant string, c int, sigma long, iter int, metric string, value double"
FAMILIES = {"dense social": "customer_part", "community": "user_hour", "web": "page_links", "purchase": "copurchase", "road": "event_chain", "short paths": "conv_chain", "small": "geo_tree", "clustered": "shared_lines", "hub-heavy": "supplier_part"}


class Graph:
    """A graph with what every workload needs of it, computed once."""

    def __init__(self, spark: SparkSession, sf_dir: str, name: str, edges: DataFrame | None = None, kept: bool = True):
        """kept: the edges are read again, for layouts and traversals; else only their degrees are."""
        self.spark, self.name = spark, name
        source = edges if edges is not None else catalog.graph(spark, sf_dir, name)
        self.edges = stored(source) if kept else source
        self.deg = stored(degrees(self.edges))
        s = degree_summary(self.deg).first()
        self.n, self.nnz, self.max_deg, self.root = s.n, s.nnz, s.max_deg, pick_root(self.deg)
        self.built: dict[tuple, L.Layout] = {}

    def layout(self, c: int = 8, sigma: int | None = None, valued: bool = False, tile: int = L.WIDE) -> L.Layout:
        key = (c, sigma, valued, tile)
        if key not in self.built:
            self.built[key] = L.build_slices(self.edges, c, sigma, valued=valued, tile_width=tile, deg=self.deg)
        return self.built[key]

    def ladder(self, c: int) -> list[int | None]:
        return [None if x >= self.n else x for x in L.sigma_ladder(self.n, c)]


def _timed(f: Callable[[], object]) -> tuple[float, object]:
    began = time.time()
    got = f()
    return time.time() - began, got


class Rows(list):
    def __init__(self, workload: str):
        super().__init__()
        self.workload = workload

    def put(self, g: str, variant: str, metric: str, value, c: int = 8, sigma: int | None = None, it: int | None = None) -> None:
        self.append((self.workload, g, variant, c, sigma, it, metric, float(value)))

    def trace(self, g: str, variant: str, result, c: int = 8, sigma: int | None = None) -> None:
        for t in result.trace.collect():
            for m in ("frontier", "slots", "skipped", "ms"):
                self.put(g, variant, m, t[m], c, sigma, t.iter)


def _sweep(rows: Rows, g: Graph, c: int, recover: bool, schedule: str, semiring: str = "tropical", workers: int = 4, scopes: tuple | None = None, timed: bool = True, **o) -> None:
    """Scopes of sorting: padding, balance and seconds of a run. Where nothing is timed, padding comes from degrees, and no slices are built."""
    ladder = list(scopes) if scopes else g.ladder(c)
    if not timed:
        for row in cost.padding_by_sigma(g.deg, c, ladder).collect():
            rows.put(g.name, schedule, "pad_slots", row.pad_slots, c, row.sigma or g.n)
        return
    for sigma in ladder:
        lay = g.layout(c, sigma)
        shown = sigma or g.n
        rows.put(g.name, schedule, "pad_slots", cost.padding_slots(lay).first()[0], c, shown)
        rows.put(g.name, schedule, "imbalance", cost.imbalance(lay, workers, schedule).first().imbalance, c, shown)
        sec, _ = _timed(lambda lay=lay: cost.drain(bfs_dense(lay, g.root, semiring, parents="recover" if recover else None, edges=g.edges, schedule=schedule, workers=workers).df))
        rows.put(g.name, schedule, "seconds", sec, c, shown)


def w01(r: Rows, g: Callable[..., Graph], **o) -> None:
    for name in ("kron", "supplier_part"):
        _sweep(r, g(name, kept=o.get("timed", True)), 8, True, "static", **o)


def w02(r: Rows, g: Callable[..., Graph], **o) -> None:
    _sweep(r, g("kron", kept=o.get("timed", True)), 8, False, "dynamic", **o)


def w03(r: Rows, g: Callable[..., Graph], **o) -> None:
    _sweep(r, g("er", kept=o.get("timed", True)), 8, True, "dynamic", **o)


def w04(r: Rows, g: Callable[..., Graph], graphs=("kron", "er", "order_part"), **o) -> None:
    for name in graphs:
        x = g(name)
        for sigma in (1, L.default_sigma(x.n, 8), None):
            for skip in (True, False):
                r.trace(name, "skip" if skip else "plain", bfs_dense(x.layout(8, sigma), x.root, "selmax", skip), 8, sigma or x.n)


def w05(r: Rows, g: Callable[..., Graph], **o) -> None:
    for name in ("kron", "order_part"):
        x = g(name)
        for s in SEMIRINGS.values():
            bfs_dense(x.layout(), x.root, s, skip=False)  # warm
            sec, got = _timed(lambda x=x, s=s: bfs_dense(x.layout(), x.root, s, skip=False))
            r.put(name, s.name, "seconds", sec)
            r.put(name, s.name, "reached", got.df.where("dist IS NOT NULL").count())
            r.put(name, s.name, "post_ops", s.post_ops)


def w06(r: Rows, g: Callable[..., Graph], timed: bool = True, **o) -> None:
    x = g("kron")
    for sigma in (16, None):  # nearly no sorting, and one scope over all rows: what the scopes of 2**4 and 2**18 stand for
        for s in SEMIRINGS.values():
            for valued in (True, False):
                lay = x.layout(8, sigma, valued)
                if timed:
                    bfs_dense(lay, x.root, s, skip=False)  # warm
                    sec, _ = _timed(lambda lay=lay, s=s: cost.drain(bfs_dense(lay, x.root, s, skip=False).df))
                    r.put(x.name, f"{s.name} {'valued' if valued else 'pattern'}", "seconds", sec, 8, sigma or x.n)
                r.put(x.name, f"{s.name} {'valued' if valued else 'pattern'}", "cells", cost.storage_cells(lay).first().cells_measured, 8, sigma or x.n)


def w07(r: Rows, g: Callable[..., Graph], **o) -> None:
    for family, name in FAMILIES.items():
        x = g(name)
        got = bfs_dense(x.layout(), x.root)
        plain = bfs_dense(x.layout(), x.root, skip=False)
        t = cost.total_work(got, plain).first()
        r.put(name, family, "work_ratio", t.ratio)
        r.put(name, family, "levels", got.df.agg(F.max("dist")).first()[0])
        for row in cost.layout_ratio(cost.storage_report(cost.padding_by_sigma(x.deg, 8, [None]))).collect():
            r.put(name, family, "cells_to_valued", row.to_valued)
            r.put(name, family, "cells_to_al", row.to_al)


def w08(r: Rows, g: Callable[..., Graph], **o) -> None:
    _sweep(r, g("kron", kept=o.get("timed", True)), 32, True, "dynamic", **o)


def w09(r: Rows, g: Callable[..., Graph], **o) -> None:
    _sweep(r, g("er", kept=o.get("timed", True)), 32, True, "dynamic", **o)


def w10(r: Rows, g: Callable[..., Graph], **o) -> None:
    x = g("kron")
    for s in SEMIRINGS:
        r.trace(x.name, s, bfs_dense(x.layout(32, 1024), x.root, s), 32, 1024)


def w11(r: Rows, g: Callable[..., Graph], **o) -> None:
    x = g("kron")
    for sigma in x.ladder(32):
        r.put(x.name, "static", "imbalance", cost.imbalance(x.layout(32, sigma), 4, "static").first().imbalance, 32, sigma or x.n)


def w12(r: Rows, g: Callable[..., Graph], tile: int = 32, **o) -> None:
    x = g("kron")
    for variant, lay in (("whole", x.layout(32, 1024)), ("tiled", x.layout(32, 1024, tile=tile))):
        r.put(x.name, variant, "imbalance", cost.imbalance(lay, 4, "static" if variant == "whole" else "tiled").first().imbalance, 32, 1024)
        r.trace(x.name, variant, bfs_dense(lay, x.root), 32, 1024)


def _kron(g: Callable[..., Graph], scale: int, factor: int) -> Graph:
    return g(f"kron {scale} {factor}", lambda spark: generate.kronecker_edges(spark, scale, factor))


def w13(r: Rows, g: Callable[..., Graph], shapes=((9, 32), (10, 16), (11, 8)), **o) -> None:
    for scale, factor in shapes:
        x = _kron(g, scale, factor)
        r.trace(x.name, "tropical", bfs_dense(x.layout(16), x.root), 16, x.n)


def _median(run: Callable, repeats: int = 3) -> float:
    """Seconds of a run after a warm-up, with its result drained: the median of the repeats."""
    cost.drain(run())
    took = sorted(_timed(lambda: cost.drain(run()))[0] for _ in range(repeats))
    return took[repeats // 2]


def _versus(r: Rows, x: Graph, c: int, semiring: str) -> None:
    """Both read what is kept in memory, are warmed up and drained, and have the same number of repeats."""
    lay = x.layout(c)
    lay.slices.persist().count()
    x.edges.persist().count()
    fast = _median(lambda: bfs_dense(lay, x.root, semiring).df)
    queue = _median(lambda: bfs_queue(x.edges, x.root))
    lay.slices.unpersist()
    x.edges.unpersist()
    r.put(x.name, "slices", "seconds", fast, c, x.n)
    r.put(x.name, "queue", "seconds", queue, c, x.n)
    r.put(x.name, "slices", "gain_percent", 100 * (queue / fast - 1), c, x.n)


def w14(r: Rows, g: Callable[..., Graph], shapes=((9, 64), (10, 32), (11, 16)), **o) -> None:
    for scale, factor in shapes:
        _versus(r, _kron(g, scale, factor), 16, "selmax")


def w15(r: Rows, g: Callable[..., Graph], factors=(128, 256, 512), **o) -> None:
    for x in (*(_kron(g, 10, f) for f in factors), g("copurchase")):
        _versus(r, x, 32, "tropical")


def w16(r: Rows, g: Callable[..., Graph], name: str = "supplier_part", runs=(1, 10, 20), **o) -> None:
    x = g(name)
    pre, lay = _timed(lambda: L.build_pattern_slices(x.edges, 8, None))
    sort, _ = _timed(lambda: cost.drain(L.sorted_positions(x.deg, None)))
    run, _ = _timed(lambda: bfs_dense(lay, x.root))
    r.put(name, "build", "seconds", pre)
    r.put(name, "sort", "seconds", sort)
    r.put(name, "traversal", "seconds", run)
    for row in cost.amortization(x.spark, pre, run, list(runs)).collect():
        r.put(name, f"{row.runs} runs", "share", row.share)


def w17(r: Rows, g: Callable[..., Graph], graphs=catalog.GRAPHS, widths=(8, 32), scopes: tuple | None = None, **o) -> None:
    for name in graphs:
        x = g(name, kept=False)
        for c in widths:
            pad = cut(cost.padding_by_sigma(x.deg, c, list(scopes) if scopes else x.ladder(c)))
            for row in cost.storage_report(pad).collect():
                r.put(name, row.layout, "cells", row.cells, c, row.sigma or x.n)


def w18(r: Rows, g: Callable[..., Graph], workers=(1, 2, 4), **o) -> None:
    """Tasks of a level instead of machines: strong scaling on one graph, weak scaling on graphs that grow with them."""
    spark = g("kron").spark

    def prepared(w: int, size: int) -> Callable:
        """Graph, layout and its deal to w tasks are made before the clock starts."""
        x = _kron(g, 10, 8 * size)
        lay = x.layout()
        per = max(1, -(-lay.chunks // w))
        dealt = replace(lay, slices=cut(lay.slices.repartition(w, F.floor(F.col("chunk_id") / per))))
        return lambda: cost.drain(bfs_dense(dealt, x.root).df)

    for mode in ("strong", "weak"):
        for row in cost.scaling(spark, prepared, list(workers), mode, 1).collect():
            r.put("kron 10", mode, f"seconds of {row.workers}", row.seconds)


def w19(r: Rows, g: Callable[..., Graph], **o) -> None:
    x = g("kron")
    r.trace(x.name, "tropical, skip, tiles", bfs_dense(x.layout(tile=256), x.root), 8, x.n)


def w20(r: Rows, g: Callable[..., Graph], graphs=catalog.GRAPHS, **o) -> None:
    for name in graphs:
        x = g(name)
        got = bfs_dense(x.layout(), x.root, skip=False)
        d = got.trace.count()
        r.put(name, "measured", "work", got.trace.agg(F.sum("slots")).first()[0])
        r.put(name, "general", "bound", cost.work_bound_general(x.n, x.nnz, 8, x.max_deg, d))
        if name == "er":
            r.put(name, "random", "bound", cost.work_bound_er(x.n, x.nnz / x.n / x.n, 8, d))
        else:
            # a graph whose degrees fall too slowly for the law has no such bound
            fit = cost.fit_power_law(degree_histogram(x.deg)).first()
            if fit.beta is not None and fit.beta > 1:
                r.put(name, "power law", "bound", cost.work_bound_powerlaw(x.n, x.nnz, 8, d, fit.alpha, fit.beta))
        for row in cost.work_table(x.spark, x.n, x.nnz // 2, d, 8, x.max_deg).collect():
            r.put(name, row.method, "asymptotic", row.work)


def w21(r: Rows, g: Callable[..., Graph], **o) -> None:
    x = g("supplier_part")
    for s in ("tropical", "boolean", "real"):
        row = cost.recovery_overhead(x.layout(), x.edges, x.root, s).first()
        r.put(x.name, s, "seconds_plain", row.seconds_plain)
        r.put(x.name, s, "seconds_recovery", row.seconds_recovery)
    sec, _ = _timed(lambda: cost.drain(bfs_dense(x.layout(), x.root, "selmax").df))
    r.put(x.name, "selmax", "seconds_plain", sec)


def w22(r: Rows, g: Callable[..., Graph], factors=(2, 8, 32, 64), **o) -> None:
    for f in factors:
        _versus(r, _kron(g, 10, f), 32, "tropical")


def w23(r: Rows, g: Callable[..., Graph], **o) -> None:
    x = g("supplier_part")
    vec = x.deg.select(F.col("id").alias("v"), F.col("deg").cast("double").alias("x"))
    csr = cut(L.build_csr(x.edges))
    by_id = vec.withColumnRenamed("v", "pos")
    forms = {"csr": lambda: product.mv_csr(csr, by_id, REAL), "csr unrolled": lambda: product.mv_csr_unrolled(csr, by_id, REAL, 4)}
    for valued in (True, False):
        lay = x.layout(valued=valued)
        at = vec.join(lay.positions, F.col("v") == F.col("id")).select("pos", "x")
        forms["valued slices" if valued else "pattern slices"] = lambda lay=lay, at=at: product.mv_slices(lay, at, REAL)
    for name, f in forms.items():
        sec, row = _timed(lambda f=f: f().agg(F.sum("y")).first())
        r.put(x.name, name, "seconds", sec)
        r.put(x.name, name, "sum", row[0])


WORKLOADS = {f"W-{i:02d}": globals()[f"w{i:02d}"] for i in range(1, 24)}


def run(spark: SparkSession, sf_dir: str, workload: str, given: dict[str, str] | None = None, **overrides) -> DataFrame:
    """given: graphs of the tables to take for generated ones, by their names."""
    made: dict[str, Graph] = {}

    def graph(name: str, edges: Callable | None = None, kept: bool = True) -> Graph:
        name = (given or {}).get(name, name)
        if name not in made:
            made[name] = Graph(spark, sf_dir, name, edges(spark) if edges else None, kept)
        return made[name]

    rows = Rows(workload)
    WORKLOADS[workload](rows, graph, **overrides)
    return spark.createDataFrame(list(rows), SCHEMA)


CLOCKED = ("seconds", "ms", "gain_percent", "share", "seconds_plain", "seconds_recovery")


def counted(spark: SparkSession, sf_dir: str, workload: str, graphs: tuple[str, ...] | None = None, metrics: tuple[str, ...] | None = None, variants: tuple[str, ...] | None = None, graphs_run: tuple[str, ...] | None = None, **overrides) -> DataFrame:
    """The rows of a workload that do not depend on the clock: counts, cells, bounds. What is run for its seconds alone is not run. Balance by dealing is left to its own query."""
    rows = run(spark, sf_dir, workload, timed=False, **overrides, **({"graphs": graphs_run} if graphs_run else {})).where(~F.col("metric").isin(*CLOCKED))
    rows = rows.where(F.col("graph").isin(*graphs)) if graphs else rows
    rows = rows.where(F.col("variant").isin(*variants)) if variants else rows
    return rows.where(F.col("metric").isin(*metrics)) if metrics else rows


def weighted_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """supplier_part with summed quantities, in both directions."""
    w = catalog.sql(spark, sf_dir, "SELECT 2 * l_suppkey AS a, 2 * l_partkey + 1 AS b, sum(l_quantity) AS w FROM {lineitem} GROUP BY l_suppkey, l_partkey")
    return w.select(F.col("a").alias("src"), F.col("b").alias("dst"), "w").unionByName(w.select(F.col("b").alias("src"), F.col("a").alias("dst"), "w"))


__all__ = ["WORKLOADS", "run", "weighted_edges"]
