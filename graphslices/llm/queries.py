"""The registered queries of the training-data operators: each applies one operator to its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphslices.llm import context_mixing, dac, dp_packing, hamming_join, learned_partitions, line_dedup, line_quality, pii_surrogates, unigram_pieces, url_templates
from graphslices.llm.common import table

URL_RULES = [
    url_templates.Rule("com", "/en/", "block"), url_templates.Rule("example.com", "/en/7", "allow"), url_templates.Rule("net", "/de/", "allow"),
    url_templates.Rule("example.net", "/de/8", "block"), url_templates.Rule("org", "/es/", "block"),
]


def op1_url_templates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A page is labelled by the label of the document of its id: bad if toxic or of low quality."""
    labels = table(spark, sf_dir, "labels").select(F.col("doc_id").alias("page_id"), F.greatest(1 - F.col("quality"), F.col("toxic")).alias("bad"))
    judged = url_templates.judge(table(spark, sf_dir, "pages").select("page_id", "url"), labels, URL_RULES)
    return judged.select("page_id", "host", "path", "rule", "verdict", "template", "purity")


def op2_pii_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii_surrogates.with_surrogates(table(spark, sf_dir, "documents").select("doc_id", "text"), pii_surrogates.surrogate_key(spark))


def op3_learned_partitions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return learned_partitions.search(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0)


def tokenizer_path(name: str = "byte_bpe_50k.json") -> str:
    """Where the public tokenizers lie: the same place on the driver and on every executor."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op4_dp_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dp_packing.pack(table(spark, sf_dir, "documents"), tokenizer_path())


def op5_unigram_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    vocabulary = unigram_pieces.load_vocabulary(tokenizer_path("piece_bpe_32k.model"))
    return unigram_pieces.encode(table(spark, sf_dir, "documents"), vocabulary)


def op6_context_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return context_mixing.score(table(spark, sf_dir, "documents"))


def op7_dac_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dac.round_trip(table(spark, sf_dir, "documents"), tokenizer_path())


def op8_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op9_line_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_quality.measures(table(spark, sf_dir, "documents").select("doc_id", "text")).drop("text")


def op10_hamming_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hamming_join.near_components(table(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_url_templates, op2_pii_surrogates, op3_learned_partitions, op4_dp_packing, op5_unigram_pieces, op6_context_mixing, op7_dac_tokens, op8_line_dedup, op9_line_quality, op10_hamming_join)}
