"""The corpus pipeline: stages over documents, each written as Parquet and read again by the next."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from subsetheavy.llm.common import stored, table
from subsetheavy.llm.decontamination import clean_docs
from subsetheavy.llm.jaccard import distinct_docs
from subsetheavy.llm.packing import packed
from subsetheavy.llm.quality import good_docs
from subsetheavy.llm.queries import tokenizer_file
from subsetheavy.llm.secrets import masked_docs
from subsetheavy.llm.tokens import token_counts
from subsetheavy.shipping import ship

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go."""
    return good_docs(docs.select(*COLUMNS), table(spark, sf_dir, "labels"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of linked shingle sets stays, that of the least doc_id. Rows are decided one by one:
    ids may repeat or be null."""
    return distinct_docs(docs.select(*COLUMNS))


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that leak a benchmark item go."""
    return clean_docs(docs.select(*COLUMNS), table(spark, sf_dir, "benchmark"))


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents stay, with their secrets masked and n_chars counted anew where that changed the text."""
    return masked_docs(docs.select(*COLUMNS))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Where each piece of each document lies in the training sequences."""
    return packed(token_counts(docs, tokenizer_file()))


STAGES = [("quality_boosted_trees", quality), ("ngram_jaccard_join", near_duplicates), ("benchmark_decontamination", decontamination), ("secret_scan", secrets), ("best_fit_packing", packing)]

#: Trained trees, alignments and a tokenizer have no SQL; tests/llm holds the method of each stage against a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = stored(stage(spark, docs, sf_dir), name)
    return docs
