"""Operations on lane arrays: arrays of C values of one type, element by element, as Spark columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from graphslices.schema import INF


def lane_load(arr: Column, i: Column | int, c: int) -> Column:
    """The i-th group of c elements."""
    return F.slice(arr, F.lit(i) * c + 1, F.lit(c))


def lane_store(chunk_id: Column, lanes: Column) -> Column:
    return F.struct(chunk_id.alias("chunk_id"), lanes.alias("lanes"))


def lane_set(*values) -> Column:
    return F.array(*[F.lit(v) for v in values])


def lane_fill(value, c: int) -> Column:
    return F.array_repeat(F.lit(value), c)


def lane_cmp(a: Column, b: Column, op: str = "=") -> Column:
    """1 where the comparison holds, else 0."""
    test = {"=": lambda x, y: x == y, "!=": lambda x, y: x != y}[op]
    return F.zip_with(a, b, lambda x, y: test(x, y).cast("bigint"))


def lane_blend(a: Column, b: Column, mask: Column) -> Column:
    """b where mask is not 0, else a."""
    return F.transform(F.arrays_zip(a.alias("a"), b.alias("b"), mask.alias("m")), lambda t: F.when(t["m"] != 0, t["b"]).otherwise(t["a"]))


def lane_min(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: F.least(x, y))


def lane_max(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: F.greatest(x, y))


def lane_add(a: Column, b: Column, saturate: bool = False) -> Column:
    if saturate:
        return F.zip_with(a, b, lambda x, y: F.when((x >= INF) | (y >= INF), F.lit(INF).cast("bigint")).otherwise(F.least(x + y, F.lit(INF).cast("bigint"))))
    return F.zip_with(a, b, lambda x, y: x + y)


def lane_mul(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x * y)


def lane_and(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: ((x != 0) & (y != 0)).cast("bigint"))


def lane_or(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: ((x != 0) | (y != 0)).cast("bigint"))


def complement(a: Column) -> Column:
    """1 where a is 0, else 0: logical negation of a vector."""
    return F.transform(a, lambda x: (x == 0).cast("bigint"))


lane_not = complement


def support(a: Column) -> Column:
    """1 where a is not 0, else 0: negated twice."""
    return F.transform(a, lambda x: (x != 0).cast("bigint"))


def lane_cast(a: Column, kind: str = "double") -> Column:
    return F.transform(a, lambda x: x.cast(kind))


def lane_gather(vector: Column, cols: Column, missing) -> Column:
    """Elements of a vector at 0-based places; a negative place, which marks padding, is never read and gives `missing`."""
    return F.transform(cols, lambda i: F.when(i >= 0, F.get(vector, i.cast("int"))).otherwise(F.lit(missing)))


def hadamard(a: Column, b: Column) -> Column:
    return lane_mul(a, b)
