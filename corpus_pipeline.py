"""A corpus pipeline of the text operators; each stage is written as Parquet and read again by the next."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from cladepack.llm.common import Scratch, table
from cladepack.llm.decontam import drop_contaminated
from cladepack.llm.exact_dedup import drop_exact_duplicates
from cladepack.llm.langid import keep_identified
from cladepack.llm.mixing import mix_sources
from cladepack.llm.ngram_join import keep_one_of_each


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a letter, or whose language stays open, go."""
    return keep_identified(docs)


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the one with the largest doc_id stays."""
    return drop_exact_duplicates(docs)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents linked by a Jaccard similarity of 0.8 over five-word shingles one stays."""
    return keep_one_of_each(docs, 5, 4, 5)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of which a twentieth or more are benchmark passages go."""
    return drop_contaminated(docs, table(spark, sf_dir, "benchmark"), 13)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """How many words a mix of the sources takes from each document."""
    return mix_sources(docs, (3, 1, 2), 1.5).select("doc_id", "source", "size", "source_size", "target", "taken", "first_slot", "n_pieces")


STAGES = [("language", language), ("exact", exact), ("near", near), ("decontaminate", decontaminate), ("mix", mix)]

# naive Bayes, near copies and their components are beyond SQL; tests hold the run against brute force
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark, "pipeline")
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = scratch.save(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
