"""Column layouts of the engine's tables and the constants in them. Unreachable is NULL outside and INF inside."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql.types import ArrayType, DoubleType, IntegerType, LongType, StructField, StructType

INF = 2**31 - 1
MARK = -1

EDGES = StructType([StructField("src", LongType()), StructField("dst", LongType())])
SLICES = StructType([StructField("chunk_id", LongType()), StructField("tile_id", IntegerType()), StructField("width", IntegerType()), StructField("col", ArrayType(LongType()))])
VALUED = StructType([*SLICES, StructField("val", ArrayType(DoubleType()))])
BFS = StructType([StructField("vertex", LongType()), StructField("dist", IntegerType()), StructField("parent", LongType())])
TRACE = "iter int, frontier long, changed long, chunks long, skipped long, slots long, ms long"


def require(df: DataFrame, *names: str) -> DataFrame:
    """df, if it has the columns; else an error that names those it lacks."""
    if missing := [n for n in names if n not in df.columns]:
        raise ValueError(f"missing columns {missing}; there are {df.columns}")
    return df
