"""Dense-frontier traversal: products of the sliced adjacency matrix with a vector, level by level.

Two physical forms behind one call. `kernel`: the vector is an array of n places that is broadcast each level, under a checked bound; the slices never move, and tasks send
back C lanes a tile. `relational` and `grid`: the state is a table, for any n; a level is a join and a partial aggregation, or a join of tiles with the segments of the vector.

Settled chunks, whose lanes are all final, are skipped: in the kernel and grid forms by a bit a chunk, before their slots are touched, in the relational one by a semi-join with the unsettled ones.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphslices import product
from graphslices.bfs.parents import recover_parents
from graphslices.layout import Layout, build_grid, restore_ids, slices_to_edges
from graphslices.schema import INF, TRACE
from graphslices.semiring import SEMIRINGS, Semiring
from graphslices.session import cut


PIECES = 8


@dataclass(frozen=True)
class BfsResult:
    """df: (vertex, dist, parent[, paths]); trace: a row for each level."""

    df: DataFrame
    trace: DataFrame


def choose_physical(layout: Layout) -> str:
    """A broadcast vector where its size allows, else the grid."""
    return "kernel" if 8 * layout.n <= product.BROADCAST_BYTES else "grid"


def bfs_dense(
    layout: Layout, root: int, semiring: str | Semiring = "tropical", skip: bool = True, parents: str | None = None, tie: str = "max", max_iter: int | None = None,
    physical: str = "auto", edges: DataFrame | None = None, col_block: int = 1 << 16, schedule: str | None = None, workers: int | None = None,
) -> BfsResult:
    """parents: None (only those that the semiring gives) or 'recover'. edges are needed for that, else they are unpacked from the layout.

    schedule: None (tiles lie as they were built), 'static' (each of `workers` tasks has as many chunks, in order) or 'dynamic' (PIECES pieces a worker, which the scheduler hands to whoever is free).
    """
    s = SEMIRINGS[semiring] if isinstance(semiring, str) else semiring
    spark = layout.slices.sparkSession
    place = layout.positions.where(F.col("id") == root).select("pos").first()
    if place is None:
        raise ValueError(f"{root} is no vertex of the layout")
    physical = choose_physical(layout) if physical == "auto" else physical
    dealt, directory = None, layout.slices
    if schedule == "static":  # equal counts of chunks a worker, whatever their widths
        k = workers or spark.sparkContext.defaultParallelism
        per = max(1, -(-layout.chunks // k))
        dealt = layout.slices.repartition(k, F.floor(F.col("chunk_id") / per))
    elif schedule == "dynamic":
        k = PIECES * (workers or spark.sparkContext.defaultParallelism)
        dealt = layout.slices.repartition(k, F.col("chunk_id") % k, "tile_id")
    elif schedule is not None:
        raise ValueError(f"unknown schedule {schedule}")
    if dealt is not None:  # the kernel packs what is dealt, and packed slices are cut
        layout = replace(layout, slices=dealt if physical == "kernel" else cut(dealt))
    if physical == "kernel":
        vector, rows = _kernel(layout, place.pos, s, skip, max_iter, directory)
    else:
        vector, rows = _relational(layout, place.pos, s, skip, max_iter, physical, col_block)
    out = restore_ids(vector, layout.positions)
    if parents == "recover" and not s.gives_parents:
        found = recover_parents(edges if edges is not None else slices_to_edges(layout), out.select("vertex", "dist"), tie)
        out = found.join(out.select("vertex", "paths"), "vertex") if "paths" in out.columns else found
    if "parent" not in out.columns:
        out = out.withColumn("parent", F.lit(None).cast("long"))
    names = ["vertex", "dist", "parent"] + (["paths"] if s.name == "real" else [])
    return BfsResult(out.select(*names), spark.createDataFrame(rows, TRACE))


def _kernel(layout: Layout, root: int, s: Semiring, skip: bool, max_iter: int | None, directory: DataFrame) -> tuple[DataFrame, list]:
    """directory: the slices wherever they lie, for their widths."""
    spark, c, chunks = layout.slices.sparkSession, layout.c, layout.chunks
    size = chunks * c
    if 8 * size > product.BROADCAST_BYTES:
        raise ValueError(f"a vector of {size} places is not broadcast; take physical='grid'")
    phantom = np.arange(size) >= layout.n
    dist = np.full(size, -1, np.int32)
    dist[root] = 0
    ids = None
    if s.gives_parents:
        got = layout.positions.select("pos", "id").toArrow()
        ids = np.zeros(size, np.int64)
        ids[np.asarray(got["pos"])] = np.asarray(got["id"]) + 1  # labels start at 1: 0 is "none"
    x = np.full(size, s.zero, s.dtype)
    x[root] = 0 if s.name == "tropical" else (ids[root] if s.gives_parents else 1)
    parent, paths = np.zeros(size, np.int64), np.zeros(size)
    if s.gives_parents:
        parent[root] = ids[root]
    paths[root] = 1
    got = directory.groupBy("chunk_id").agg(F.sum(F.col("width").cast("long") * c).alias("slots"), F.count("*").alias("tiles")).toArrow()  # a row a chunk, under the same bound
    tiled = bool((np.asarray(got["tiles"]) > 1).any())
    slots = np.zeros(chunks, np.int64)
    slots[np.asarray(got["chunk_id"])] = np.asarray(got["slots"])
    rows, level = [], 0
    while max_iter is None or level < max_iter:
        settled = ((dist >= 0) | phantom).reshape(chunks, c).all(axis=1)
        if settled.all():
            break
        level += 1
        began = time.time()
        # distances fit half the bytes; lanes of settled chunks tell nothing new, but to labels, which are set again where a neighbour has one
        sent = spark.sparkContext.broadcast((x.astype(np.int32) if s.name == "tropical" else x, settled if skip else None, None if skip or s.gives_parents else settled))  # bounded by BROADCAST_BYTES
        partial = product.packed_partials(layout, sent, s)
        # a chunk of several tiles is summed where the tiles are: C lanes a chunk come back, under the bound of the vector, however many tiles a hub has
        partial = (product.merge_lanes(partial, s, c) if tiled else partial).toArrow()
        sent.destroy()
        y = np.full((chunks, c), s.zero, s.dtype)
        if partial.num_rows:
            s.np_plus.at(y, np.asarray(partial["chunk_id"]), np.asarray(partial["lanes"].combine_chunks().flatten()).reshape(-1, c))
        y = y.ravel()
        new = (y < INF if s.name == "tropical" else y > 0) & (dist < 0)
        dist[new] = level
        if s.name == "tropical":
            x = np.minimum(x, y)
        elif s.name == "real":
            x = np.where(new, y, 0.0)
            paths[new] = y[new]
        elif s.name == "boolean":
            x = new.astype(s.dtype)
        else:
            parent[new] = y[new]
            hit = (y > 0) | (np.repeat(settled, c) & (x > 0) if skip else False)
            x = np.where(hit, ids, 0)
        run = ~settled if skip else np.ones(chunks, bool)
        k = int(new.sum())
        rows.append((level, k, k, int(run.sum()), int((~run).sum()), int(slots[run].sum()), int(1000 * (time.time() - began))))
        if not k:
            break
    import pyarrow as pa

    real = np.flatnonzero(~phantom)
    cols = {"pos": real, "dist": pa.array(dist[real], mask=dist[real] < 0)}
    if s.gives_parents:
        cols["parent"] = pa.array(parent[real] - 1, mask=parent[real] == 0)
    if s.name == "real":
        cols["paths"] = paths[real]
    return spark.createDataFrame(pa.table(cols)), rows


def _relational(layout: Layout, root: int, s: Semiring, skip: bool, max_iter: int | None, physical: str, col_block: int) -> tuple[DataFrame, list]:
    c, ids = layout.c, layout.positions
    first = F.col("pos") == root
    label = F.col("id") + 1
    start = {"tropical": F.when(first, 0), "boolean": F.when(first, 1), "real": F.when(first, 1.0), "selmax": F.when(first, label)}[s.name]
    state = cut(
        ids.select("pos", "id", start.cast(s.sql_type).alias("x"), F.when(first, 0).alias("dist"), F.when(first, F.col("id")).alias("parent"), F.when(first, 1.0).alias("paths"))
    )
    widths = cut(layout.slices.groupBy("chunk_id").agg(F.sum(F.col("width").cast("long") * c).alias("slots")))
    grid = build_grid(layout, col_block) if physical == "grid" else None
    rows, level = [], 0
    while max_iter is None or level < max_iter:
        level += 1
        began = time.time()
        opened = state.where("dist IS NULL").select(F.floor(F.col("pos") / c).alias("chunk_id")).distinct()
        todo = cut(widths.join(opened, "chunk_id", "left_semi") if skip else widths)
        run, slots = todo.agg(F.count("*"), F.coalesce(F.sum("slots"), F.lit(0))).first()
        if not run or (not skip and opened.isEmpty()):
            break
        vector = state.where("x IS NOT NULL").select("pos", "x")
        if grid is not None:
            y = product.mv_grid(grid, vector, s, product.chunk_bits(todo, layout.chunks) if skip else None)
        else:
            source = layout.slices.join(todo.select("chunk_id"), "chunk_id", "left_semi") if skip else layout.slices
            y = product.mv_slices(replace(layout, slices=source, valued=False), vector, s)
        new = F.col("y").isNotNull() & F.col("dist").isNull()
        nxt = {
            "tropical": F.coalesce(F.least("x", "y"), "x", "y"), "boolean": F.when(new, F.lit(1)), "real": F.when(new, F.col("y")),
            "selmax": F.when(F.col("y").isNotNull() | F.col("x").isNotNull(), label),
        }[s.name]
        joined = state.join(y.withColumnRenamed("row", "pos"), "pos", "left")
        state = cut(joined.select(
            "pos", "id", nxt.cast(s.sql_type).alias("x"), F.when(new, level).otherwise(F.col("dist")).alias("dist"),
            F.when(new, F.col("y").cast("long") - 1).otherwise(F.col("parent")).alias("parent"), F.when(new, F.col("y").cast("double")).otherwise(F.col("paths")).alias("paths"),
        ))
        k = state.where(F.col("dist") == level).count()
        rows.append((level, k, k, run, layout.chunks - run, slots, int(1000 * (time.time() - began))))
        if not k:
            break
    keep = ["pos", "dist"] + (["parent"] if s.gives_parents else []) + (["paths"] if s.name == "real" else [])
    out = state.select(*keep)
    return (out.fillna({"paths": 0.0}) if s.name == "real" else out), rows


def bfs_many(layout: Layout, roots: list[int], **options) -> DataFrame:
    """(root, vertex, dist, parent) of several traversals of one layout."""
    out = None
    for r in roots:
        one = bfs_dense(layout, r, **options).df.withColumn("root", F.lit(r).cast("long"))
        out = one if out is None else out.unionByName(one)
    return out
