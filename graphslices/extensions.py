"""Further uses of the same products and traversals."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphslices import product
from graphslices.edges import degrees, pick_root
from graphslices.layout import Layout
from graphslices.semiring import REAL
from graphslices.session import cut


def pagerank(layout: Layout, iters: int = 10, damping: float = 0.85) -> DataFrame:
    """(vertex, rank) by products of the same slices over the real semiring; rank of rows without neighbours is dealt to all."""
    n = layout.n
    p = layout.positions.select("pos", "id", "deg")
    state = cut(p.withColumn("r", F.lit(1.0 / n)))
    for _ in range(iters):
        sent = state.where("deg > 0").select("pos", (F.col("r") / F.col("deg")).alias("x"))
        lost = state.where("deg = 0").agg(F.coalesce(F.sum("r"), F.lit(0.0))).first()[0]
        y = product.mv_tiles(layout, sent, REAL) if 8 * n <= product.BROADCAST_BYTES else product.mv_slices(layout, sent, REAL)
        joined = p.join(y.withColumnRenamed("row", "pos"), "pos", "left")
        state = cut(joined.withColumn("r", (1 - damping) / n + damping * (F.coalesce("y", F.lit(0.0)) + lost / n)).drop("y"))
    return state.select(F.col("id").alias("vertex"), F.col("r").alias("rank"))


def betweenness_from_root(edges: DataFrame, bfs: DataFrame) -> DataFrame:
    """(vertex, dependency): how much of the root's shortest paths leads through each vertex, from a result with paths: sums from the last level back."""
    d = cut(bfs.where("dist IS NOT NULL").select("vertex", "dist", "paths"))
    depth = d.agg(F.max("dist")).first()[0]
    down = edges.join(d.select(F.col("vertex").alias("src"), F.col("dist").alias("ds"), F.col("paths").alias("ps")), "src").join(
        d.select(F.col("vertex").alias("dst"), F.col("dist").alias("dd"), F.col("paths").alias("pd")), "dst").where("dd = ds + 1")
    down = cut(down.select("src", "dst", "dd", (F.col("ps") / F.col("pd")).alias("share")))
    got = cut(d.where(F.col("dist") == depth).select("vertex", F.lit(0.0).alias("dependency")))
    out = got
    for level in range(depth, 0, -1):
        step = down.where(F.col("dd") == level).join(got.select(F.col("vertex").alias("dst"), "dependency"), "dst", "left")
        sums = step.groupBy(F.col("src").alias("vertex")).agg(F.sum(F.col("share") * (1 + F.coalesce("dependency", F.lit(0.0)))).alias("dependency"))
        got = cut(d.where(F.col("dist") == level - 1).select("vertex").join(sums, "vertex", "left").select("vertex", F.coalesce("dependency", F.lit(0.0)).alias("dependency")))
        out = out.unionByName(got)
    return out


def odd_cycle_edges(edges: DataFrame, bfs: DataFrame) -> DataFrame:
    """Edges inside a level: the component of the root is bipartite if there are none."""
    d = bfs.where("dist IS NOT NULL").select("vertex", "dist")
    both = edges.where("src < dst").join(d.select(F.col("vertex").alias("src"), F.col("dist").alias("ds")), "src").join(d.select(F.col("vertex").alias("dst"), F.col("dist").alias("dd")), "dst")
    return both.where("(ds - dd) % 2 = 0").select("src", "dst")


def augmenting_path(residual: DataFrame, source: int, sink: int) -> list[int]:
    """Vertices of a shortest path of a directed residual graph (src, dst); [] if there is none. One row a level comes to the driver."""
    from graphslices.bfs import bfs_queue, recover_parents

    bfs = cut(recover_parents(residual, bfs_queue(residual, source)))
    path, at = [sink], bfs.where(F.col("vertex") == sink).first()
    if at is None or at.dist is None:
        return []
    while path[-1] != source:
        path.append(bfs.where(F.col("vertex") == path[-1]).first().parent)
    return path[::-1]


def double_sweep(edges: DataFrame, sweeps: int = 2) -> int:
    """A lower bound of the diameter: traversals from the last one's farthest vertex."""
    from graphslices.bfs import bfs_queue

    root, best = pick_root(degrees(edges)), 0
    for _ in range(sweeps):
        far = bfs_queue(edges, root).where("dist IS NOT NULL").orderBy(F.desc("dist"), "vertex").first()
        root, best = far.vertex, max(best, far.dist)
    return best


def active_column_blocks(grid: DataFrame, vector: DataFrame, col_block: int) -> DataFrame:
    """Grid tiles whose columns have a value in a sparse vector: the others bring nothing."""
    return grid.join(vector.select(F.floor(F.col("pos") / col_block).alias("col_block")).distinct(), "col_block", "left_semi")
