"""The ``opN_<name>`` queries over the whole given tables, and the SQL of those that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from blockgraph.llm import bloom_lm, decontaminate, html_text, jaccard, mixing, ogg, oracles, quality, substring_dedup, suffix_dedup, tokens
from blockgraph.llm.shared import table

VOCABULARY = "byte_bpe_50k.json"


def vocabulary_path(name: str = VOCABULARY) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_ogg(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ogg.read(ogg.encode(table(spark, sf_dir, "documents")))


def op2_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op3_bloom_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bloom_lm.score(table(spark, sf_dir, "documents"))


def op4_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.join(table(spark, sf_dir, "documents"))


def op5_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.find(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op6_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract(table(spark, sf_dir, "pages"))


def op7_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.digest(table(spark, sf_dir, "documents"))


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op9_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokens.count_tokens(table(spark, sf_dir, "documents"), vocabulary_path())


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.digest(table(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_ogg, op2_mix, op3_bloom_lm, op4_jaccard, op5_decontaminate, op6_html_text, op7_suffix_dedup, op8_quality, op9_tokens, op10_substring_dedup)}
ORACLE_SQL = {"op2_mix": mixing.MIX_SQL.format(docs="documents"), "op4_jaccard": oracles.JACCARD, "op7_suffix_dedup": oracles.SUFFIX, "op10_substring_dedup": oracles.SUBSTRING}
