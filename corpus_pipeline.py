"""A training-data pipeline over `documents`: quality rules, line dedup, near-duplicate removal, surrogates for personal data, packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame that run() writes as Parquet to the shared folder and reads again as the next stage's docs. All but the last
return the columns of docs, in their order.

Edge cases, stage by stage, are those of the operators: a document with a null or empty text has no words and goes with the quality rules; in the later stages, taken alone, it stays as it is, links with nothing
and is packed as the end mark alone. A null doc_id is no place of its own in line dedup (it sorts first), links with nothing, stays, and is packed first. Texts of any length are judged, compared, scanned
and packed whole. Ties go to the smaller doc_id; repeated rows of one doc_id and text are kept or dropped together by all stages but near-duplicates, which keeps all rows of the document it keeps. An empty
table passes every stage as an empty table. Columns besides doc_id and text are carried through all stages but packing, whatever their names (n_chars, where it is there, is told anew); names that begin with `__` are the operators' own.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphslices.llm import dp_packing, hamming_join, line_dedup, line_quality, pii_surrogates
from graphslices.llm.common import table, written
from graphslices.llm.queries import tokenizer_path

# Near copies of this stage are pairs of a similarity of 0.8 or more; op10's own default is 0.85. 16 chunks with one error each reach distance 31,
# which a pair at 0.8 leaves with a chance of less than a millionth.
NEAR = hamming_join.HammingJoin(percent=80, chunks=16, distance=31)


def _sized(docs: DataFrame) -> DataFrame:
    """docs with n_chars, if they have it, told anew after a change of the text."""
    return docs.withColumn("n_chars", F.length("text").cast(dict(docs.dtypes)["n_chars"])) if "n_chars" in docs.columns else docs


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Failing lines and rejected documents go."""
    return _sized(line_quality.clean(docs))


def dedup_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines seen earlier go, and documents that had nothing else."""
    done = line_dedup.dedup_lines(docs)
    return _sized(done.where((F.col("n_kept") > 0) | (F.col("n_lines") == 0)).select(*docs.columns))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies the document with the least id stays."""
    kept = hamming_join.near_components(docs, NEAR).where("kept").select(F.col("doc_id").alias("__kept")).distinct()
    return docs.join(kept, F.equal_null(F.col("doc_id").cast("long"), F.col("__kept")), "left_semi").select(*docs.columns)


def surrogates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data and secrets are replaced, under the session's key; no document goes."""
    return _sized(pii_surrogates.with_surrogates(docs, pii_surrogates.surrogate_key(spark), count=None))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of documents in sequences of at most 1024 ids."""
    return dp_packing.pack(docs, tokenizer_path())


STAGES = [
    ("quality rules", quality_rules), ("line dedup", dedup_lines), ("near-duplicates", near_duplicates), ("surrogates", surrogates), ("packing", packing),
]
# Signatures, surrogates and packing have no SQL form; tests compare run() with a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
