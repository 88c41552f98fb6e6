"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def main() -> None:
    from pyspark.sql import functions as F

    from graphslices import catalog, cost, edges as E, layout as L
    from graphslices.bfs import bfs_dense, bfs_queue
    from graphslices.session import cut, local_session

    spark = local_session(CPUS, int(CPUS) if CPUS.isdigit() else 8, "8g")
    spark.sparkContext.setLogLevel("ERROR")
    took: dict[str, float] = {}
    facts: dict[str, float] = {}

    def clock(name: str, f):
        began = time.time()
        got = f()
        took[name] = round(time.time() - began, 3)
        return got

    def median(name: str, f, repeats: int = 3) -> float:
        """Of some repeats after a warm-up, each drained to the end."""
        cost.drain(f())
        runs = []
        for _ in range(repeats):
            began = time.time()
            cost.drain(f())
            runs.append(time.time() - began)
        took[name] = round(sorted(runs)[repeats // 2], 3)
        return took[name]

    spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count().collect()  # starts the engine
    warm = cut(catalog.graph(spark, SF_DIR, "geo_tree"))
    bfs_dense(L.build_pattern_slices(warm, 8, None), E.pick_root(E.degrees(warm)))  # code is compiled, workers are up
    for name in ("supplier_part", "customer_part", "order_part", "copurchase", "kron", "er", "event_chain"):
        edges = clock(f"{name}: edges", lambda name=name: cut(catalog.graph(spark, SF_DIR, name)))
        edges.persist().count()
        root = E.pick_root(E.degrees(edges))
        pattern = clock(f"{name}: build pattern slices", lambda edges=edges: L.build_pattern_slices(edges, 8, None))
        pattern.slices.persist().count()
        repeats = 1 if name == "event_chain" else 3
        skip = median(f"{name}: slices, tropical, skip", lambda pattern=pattern, root=root: bfs_dense(pattern, root).df, repeats)
        median(f"{name}: slices, selmax, skip", lambda pattern=pattern, root=root: bfs_dense(pattern, root, "selmax").df, repeats)
        whole = median(f"{name}: slices, tropical, no skip", lambda pattern=pattern, root=root: bfs_dense(pattern, root, skip=False).df, repeats)
        queue = median(f"{name}: tuned queue", lambda edges=edges, root=root: bfs_queue(edges, root), repeats)
        work = cost.total_work(bfs_dense(pattern, root), bfs_dense(pattern, root, skip=False)).first()
        cells = cost.cells_exact(pattern.n, pattern.nnz, cost.padding_slots(pattern).first()[0], 8)
        build = took[f"{name}: build pattern slices"]
        facts |= {
            f"{name}: work with skip over without": work.ratio, f"{name}: cells pattern over valued": round(cells["pattern"] / cells["valued"], 4),
            f"{name}: cells pattern over adjacency list": round(cells["pattern"] / cells["al"], 4), f"{name}: gain of skipping, percent": round(100 * (whole / skip - 1), 1),
            f"{name}: gain over tuned queue, percent": round(100 * (queue / skip - 1), 1), f"{name}: preprocessing share of 20 runs": round(build / (build + 20 * skip), 4),
        }
        pattern.slices.unpersist()
        edges.unpersist()
    total = round(sum(v for k, v in took.items() if "slices, tropical, skip" in k and k.split(":")[0] in ("supplier_part", "customer_part", "order_part", "copurchase")), 3)
    print(json.dumps({"metric": "seconds of the flagship traversal over four graphs", "value": total, "unit": "sec", "queries": took, "facts": facts, "sf": SF_DIR.rstrip("/").rsplit("/", 1)[-1].removeprefix("sf")}))
    spark.stop()


if __name__ == "__main__":
    sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
    main()
