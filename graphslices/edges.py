"""Edges as (src, dst) rows: clean-up, degrees, roots."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphslices.schema import require


def normalize_edges(df: DataFrame, src: str = "src", dst: str = "dst", directed: bool = False, drop_loops: bool = True, once: bool = False) -> DataFrame:
    """Distinct edges, in both directions unless directed. once: the rows are known to be distinct, none the reverse of another."""
    require(df, src, dst)
    one = df.select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst")).where("src IS NOT NULL AND dst IS NOT NULL")
    if drop_loops:
        one = one.where("src <> dst")
    if not directed:
        # one pass over the input: both directions leave each row, before the single shuffle
        one = one.select(F.explode(F.array(F.struct("src", "dst"), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst")))).alias("e")).select("e.*")
    return one if once else one.distinct()


def transpose_edges(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *[c for c in edges.columns if c not in ("src", "dst")])


def vertex_set(edges: DataFrame, extra: DataFrame | None = None) -> DataFrame:
    """(id) of all ends, and of `extra` (id), where isolated vertices come from."""
    ids = edges.select(F.explode(F.array("src", "dst")).alias("id"))
    if extra is not None:
        ids = ids.unionByName(extra.select(F.col("id").cast("long")))
    return ids.distinct()


def degrees(edges: DataFrame, vertices: DataFrame | None = None) -> DataFrame:
    """(id, deg) by rows of the adjacency matrix; with `vertices`, isolated ones have degree 0."""
    deg = edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("deg"))
    if vertices is None:
        return deg
    return vertices.join(deg, "id", "left").select("id", F.coalesce("deg", F.lit(0).cast("long")).alias("deg"))


def all_degrees(edges: DataFrame, extra: DataFrame | None = None) -> DataFrame:
    """(id, deg) of every end of an edge and of `extra` (id), ends without a row of their own with degree 0: one aggregation."""
    ends = edges.select(F.explode(F.array(F.struct(F.col("src").alias("id"), F.lit(1).alias("k")), F.struct(F.col("dst").alias("id"), F.lit(0).alias("k")))).alias("e")).select("e.*")
    if extra is not None:
        ends = ends.unionByName(extra.select(F.col("id").cast("long"), F.lit(0).alias("k")))
    return ends.groupBy("id").agg(F.sum("k").alias("deg"))


def degree_summary(deg: DataFrame) -> DataFrame:
    """One row: n, nnz, largest degree, slots a row and edges a row (half of that)."""
    return deg.agg(
        F.count("*").alias("n"), F.coalesce(F.sum("deg"), F.lit(0)).alias("nnz"), F.coalesce(F.max("deg"), F.lit(0)).alias("max_deg"),
        F.round(F.avg("deg"), 6).alias("slots_per_row"), F.round(F.avg("deg") / 2, 6).alias("edges_per_row"),
    )


def degree_histogram(deg: DataFrame) -> DataFrame:
    return deg.groupBy("deg").agg(F.count("*").alias("cnt"))


def pick_root(deg: DataFrame, policy: str = "max") -> int | None:
    """The vertex of highest (max) or lowest non-zero (min) degree, ties to the lowest id; None without vertices."""
    order = F.desc("deg") if policy == "max" else F.asc("deg")
    row = deg.where("deg > 0").orderBy(order, "id").first() or deg.orderBy("id").first()
    return row["id"] if row else None


def reachable(bfs: DataFrame) -> DataFrame:
    return bfs.where("dist IS NOT NULL")


def bfs_depth(bfs: DataFrame) -> int | None:
    return bfs.agg(F.max("dist")).first()[0]


def project_pairs(df: DataFrame, left: str, right: str) -> DataFrame:
    """Pairs a < b of left values that share a right value."""
    p = df.select(F.col(left).alias("a"), F.col(right).alias("r")).distinct()
    return p.join(p.withColumnRenamed("a", "b"), "r").where("a < b").select("a", "b").distinct()


def global_rank(df: DataFrame, *order) -> DataFrame:
    """df with `pos`, its place from 0 in a total order, without a window over all rows: ranges are sorted apart, and the counts of the ranges before are added."""
    from graphslices.session import stored

    # the id of a row holds its partition and its place in it: no window, and no shuffle beside the one by ranges
    ranged = stored(df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("__at", F.monotonically_increasing_id()))
    part, local = F.shiftright("__at", 33), F.col("__at").bitwiseAND(F.lit((1 << 33) - 1))
    counts = ranged.groupBy(part.alias("__part")).agg(F.count("*").alias("__n"))  # a row for each range
    before = counts.select("__part", F.coalesce(F.sum("__n").over(Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("__base"))
    return ranged.join(F.broadcast(before), part == F.col("__part")).withColumn("pos", (local + F.col("__base")).cast("long")).drop("__part", "__at", "__base")
