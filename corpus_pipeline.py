"""Five corpus stages over the documents table: quality, near duplicates, repeated substrings, leaked benchmark items, mixing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from blockgraph.llm import decontaminate, jaccard, mixing, quality, suffix_dedup
from blockgraph.llm.shared import cut, table


def classified(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the documents that the quality classifier (operator 8) does not reject."""
    return quality.keep_good(docs, quality.fit(docs, table(spark, sf_dir, "labels")))


def without_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the smallest doc_id of each group of near duplicates (operator 4)."""
    return jaccard.keep_one(docs)


def without_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cuts out of the texts what 100-byte strings repeat (operator 7); every document stays, n_chars is counted anew."""
    return suffix_dedup.remove(docs)


def without_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that hold a benchmark item (operator 5); each row is judged by its own text."""
    return decontaminate.remove(docs, table(spark, sf_dir, "benchmark"))


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents with how many of their words the mix of sources takes (operator 2): taken of size, repetitions counted."""
    return mixing.mix(docs, carry=tuple(c for c in docs.columns if c not in ("doc_id", "source")))


STAGES = [("quality", classified), ("near-duplicates", without_near_duplicates), ("repeats", without_repeats), ("leaks", without_leaks), ("mix", mixed)]
#: The classifier is trained, so SQL cannot give the rows; tests/llm holds every stage against a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The corpus after all stages in turn, texts included, for the caller to write; each stage's rows are written to the shared folder
    and read by the next, and those folders go when the application ends."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir), f"stage-{name}", free=True)
    return STAGES[-1][1](spark, docs, sf_dir)
