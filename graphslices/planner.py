"""A traversal's plan before it runs: what to store, skip, tile, gather and when to leave dense products, as rules over one small record."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame

from graphslices import product
from graphslices.bfs.dense import BfsResult, bfs_dense
from graphslices.bfs.frontier import bfs_queue
from graphslices.layout import WIDE, Layout, tile_slices
from graphslices.schema import TRACE


@dataclass(frozen=True)
class TraversalPlan:
    n: int
    nnz: int
    c: int = 8
    semiring: str = "tropical"
    values: bool = True
    skip: bool = False
    tile_width: int | None = None
    widest: int = 0
    gather: str = "kernel"
    method: str = "dense"
    depth_guess: int = 0
    applied: tuple[str, ...] = ()


def drop_implied_values(p: TraversalPlan) -> TraversalPlan:
    """Values of an unweighted graph follow from the pattern: they are neither stored nor read."""
    return replace(p, values=False, applied=(*p.applied, "DropImpliedValues")) if p.values else p


def skip_settled(p: TraversalPlan) -> TraversalPlan:
    return replace(p, skip=True, applied=(*p.applied, "SkipSettled")) if p.method == "dense" and not p.skip else p


def tile_wide_chunks(p: TraversalPlan) -> TraversalPlan:
    """A chunk wider than a tile is split, so no row of the layout grows with a hub."""
    if p.widest > WIDE and p.tile_width is None:
        return replace(p, tile_width=WIDE, applied=(*p.applied, "TileWideChunks"))
    return p


def choose_gather(p: TraversalPlan) -> TraversalPlan:
    """A vector under the broadcast bound goes to the slices, a larger one meets them by blocks of columns."""
    want = "kernel" if 8 * p.n <= product.BROADCAST_BYTES else "grid"
    return replace(p, gather=want, applied=(*p.applied, f"ChooseGather({want})")) if want != p.gather or not any("ChooseGather" in a for a in p.applied) else p


def switch_direction(p: TraversalPlan, deep: int = 64) -> TraversalPlan:
    """Graphs of many thin levels are left to the queue."""
    return replace(p, method="queue", applied=(*p.applied, "SwitchDirection")) if p.depth_guess > deep and p.method == "dense" else p


def plan_for(layout: Layout, semiring: str = "tropical") -> TraversalPlan:
    """What the layout tells: sizes, the widest chunk, and a guess of the depth. Thin graphs, whose largest degree is small, can only be deep: each level reaches at most that many more a vertex."""
    from pyspark.sql import functions as F

    top = layout.positions.agg(F.max("deg")).first()[0] or 0
    depth = 0 if top > 4 else layout.n // max(1, top) if layout.nnz else 0
    return TraversalPlan(layout.n, layout.nnz, layout.c, semiring, values=layout.valued, widest=top, depth_guess=depth)


RULES = (drop_implied_values, switch_direction, skip_settled, tile_wide_chunks, choose_gather)


def rewrite(p: TraversalPlan) -> TraversalPlan:
    for rule in RULES:
        p = rule(p)
    return p


def explain(p: TraversalPlan) -> str:
    return f"{p.method} over {'valued' if p.values else 'pattern'} slices (C={p.c}), {p.semiring}, gather={p.gather}, skip={p.skip}, tiles={p.tile_width or 'none'}; rules: {', '.join(p.applied) or 'none'}"


def run(p: TraversalPlan, layout: Layout, edges: DataFrame, root: int) -> BfsResult:
    if p.method == "queue":
        from pyspark.sql import functions as F

        df = bfs_queue(edges, root).withColumn("parent", F.lit(None).cast("long"))
        return BfsResult(df, edges.sparkSession.createDataFrame([], TRACE))
    if p.tile_width and p.tile_width < layout.tile_width:
        layout = tile_slices(layout, p.tile_width)
    return bfs_dense(layout, root, p.semiring, p.skip, physical=p.gather, edges=edges)
