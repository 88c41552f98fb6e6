"""Helpers shared by the training-data operators: table access, shared storage, small column tools."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from graphslices.session import cut, shared_dir

__all__ = ["LOWER", "NOT_WHITE", "UPPER", "WHITE", "ascii_lower", "cut", "let", "shared_dir", "shared_path", "table", "words_of", "written"]
WHITE = r"[\x20\x09-\x0D]"
NOT_WHITE = r"[^\x20\x09-\x0D]"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_path(spark: SparkSession, what: str) -> str:
    return f"{shared_dir(spark)}/graphslices-{what}-{uuid.uuid4().hex}"


def written(df: DataFrame, what: str) -> DataFrame:
    """df as a Parquet table in the shared folder, read again with the schema it was written with."""
    spark, path = df.sparkSession, shared_path(df.sparkSession, what)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def let(value: Column, body) -> Column:
    """body(value) with value computed once for a row, however often body names it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def words_of(text: Column) -> Column:
    """The words of a text: its runs of characters other than ASCII white space; null gives none."""
    # every white space as a blank: a split at one plain character needs no pattern
    plain = F.coalesce(text, F.lit(""))
    for c in "\t\n\x0b\x0c\r":
        plain = F.replace(plain, F.lit(c), F.lit(" "))
    return F.array_remove(F.split(plain, " "), "")


def ascii_lower(text: Column) -> Column:
    return F.translate(text, UPPER, LOWER)
