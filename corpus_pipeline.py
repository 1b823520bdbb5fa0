"""The corpus pipeline: quality rules, near duplicates, decontamination, pseudonyms and packing, each on what its predecessor kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from starfold.llm import decontaminate, neardup, packing, private, quality
from starfold.llm.queries import TOKENIZER, private_key
from starfold.llm.shared import discard, documents, scratch, stored, table


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rule or the outlier test rejects go."""
    return quality.filter_documents(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near duplicates stays, that of least id."""
    return neardup.keep_one(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Benchmark passages are cut out; documents that are mostly benchmark go."""
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark"))


def pseudonyms(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Private values are replaced by format-preserving pseudonyms."""
    return private.pseudonymize(docs, key=private_key(spark), count=None)


def best_fit_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document as pieces of sequences of at most 4096 ids."""
    return packing.pack_documents(docs, TOKENIZER)


STAGES = [
    ("quality_rules", quality_rules),
    ("near_duplicates", near_duplicates),
    ("decontamination", decontamination),
    ("pseudonyms", pseudonyms),
    ("best_fit_packing", best_fit_packing),
]

#: Packing and the estimates of the quality rules have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last stage's rows. What a stage writes for itself is deleted once its result is written, and that once the next one is."""
    docs = documents(spark, sf_dir)
    for _, stage in STAGES:
        before = docs
        with scratch() as made:
            docs = stored(stage(spark, docs, sf_dir))
            made[:] = [t for t in made if t is not docs]
        discard(before)
    return docs
