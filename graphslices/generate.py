"""Generated graphs by integer arithmetic alone, so that every engine draws the same edges."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from graphslices.edges import normalize_edges

PRIME = 2**31 - 1


def mix(z: Column) -> Column:
    """A scrambled residue; no product passes 2**62."""
    r = z % PRIME
    return ((r * r) % PRIME * 48271 + 11) % PRIME


def mix_sql(z: str) -> str:
    return f"(((({z}) % {PRIME}) * (({z}) % {PRIME})) % {PRIME} * 48271 + 11) % {PRIME}"


def kronecker_pairs(spark: SparkSession, scale: int = 11, edge_factor: int = 16, seed: int = 42, probs: tuple[int, int, int, int] = (57, 19, 19, 5)) -> DataFrame:
    """Raw pairs (a, b) of a power-law Kronecker graph: each edge draws one quadrant a bit, with the given per cents."""
    a, b, c, _ = probs
    i = F.col("id")
    src, dst = F.lit(0).cast("long"), F.lit(0).cast("long")
    for k in range(scale):
        r = mix(i * 73856093 + k * 19349663 + seed) % 100
        src = src + F.when(r >= a + b, 1 << k).otherwise(0)
        dst = dst + F.when(((r >= a) & (r < a + b)) | (r >= a + b + c), 1 << k).otherwise(0)
    return spark.range(edge_factor << scale).select(src.alias("a"), dst.alias("b"))


def kronecker_edges(spark: SparkSession, scale: int = 11, edge_factor: int = 16, seed: int = 42, probs: tuple[int, int, int, int] = (57, 19, 19, 5)) -> DataFrame:
    return normalize_edges(kronecker_pairs(spark, scale, edge_factor, seed, probs), "a", "b")


def er_edges_pairs(spark: SparkSession, n: int = 2048, p_num: int = 16776557) -> DataFrame:
    """Every pair of n vertices with chance p_num / PRIME: quadratic, for n up to some thousands."""
    if n > 1 << 14:
        raise ValueError("for larger n take er_edges_sampled")
    row = spark.range(n).select(F.col("id").alias("a"), F.explode(F.sequence(F.col("id") + 1, F.lit(n))).alias("b")).where(F.col("b") < n)
    return normalize_edges(row.where(mix(F.col("a") * 73856093 + F.col("b") * 19349663) < p_num), "a", "b")


def er_edges_sampled(spark: SparkSession, n: int, m: int, seed: int = 7) -> DataFrame:
    """About m edges between n vertices, drawn edge by edge: linear in m, for any size."""
    i = F.col("id")
    draw = lambda k: mix(mix(i * 2 + k + seed) + i * 31 + k) % n
    return normalize_edges(spark.range(m).select(draw(0).alias("a"), draw(1).alias("b")), "a", "b")


def _kron_sql(scale: int = 11, edge_factor: int = 16, seed: int = 42) -> str:
    r = mix_sql(f"i * 73856093 + k * 19349663 + {seed}") + " % 100"
    return f"""SELECT cast(sum(CASE WHEN r >= 76 THEN 1 << k ELSE 0 END) AS BIGINT) AS a, cast(sum(CASE WHEN (r >= 57 AND r < 76) OR r >= 95 THEN 1 << k ELSE 0 END) AS BIGINT) AS b
        FROM (SELECT i, k, ({r.replace(' % 100', '')}) % 100 AS r FROM range({edge_factor << scale}) t(i), range({scale}) u(k)) GROUP BY i"""


KRON_SQL = _kron_sql()
ER_SQL = f"SELECT i AS a, j AS b FROM range(2048) t(i), range(2048) u(j) WHERE i < j AND {mix_sql('i * 73856093 + j * 19349663')} < 16776557"
