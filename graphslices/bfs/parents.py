"""Parents from distances."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphslices.layout import PLACES_BYTES


def recover_parents(edges: DataFrame, dist: DataFrame, tie: str = "max") -> DataFrame:
    """(vertex, dist, parent) from (vertex, dist): a neighbour one level nearer, the root being its own parent. Unreachable vertices take no part, as infinity less one is infinity."""
    n = dist.count()
    sent = F.broadcast if 32 * n <= PLACES_BYTES else lambda df: df  # distances under a checked bound go to the edges, as places do
    near = dist.where("dist IS NOT NULL").select("vertex", "dist")
    steps = edges.join(sent(near.select(F.col("vertex").alias("src"), F.col("dist").alias("ds"))), "src").join(sent(near.select(F.col("vertex").alias("dst"), F.col("dist").alias("dd"))), "dst")
    pick = F.max("src") if tie == "max" else F.min("src")
    up = steps.where("ds = dd - 1").groupBy(F.col("dst").alias("vertex")).agg(pick.alias("parent"))
    return dist.select("vertex", "dist").join(up, "vertex", "left").withColumn("parent", F.when(F.col("dist") == 0, F.col("vertex")).otherwise(F.col("parent")))
