"""Queries of the ten operators, each over its whole table with production parameters."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import functions as F

from starfold.llm import decontaminate, language, licenses, neardup, packing, private, quality, sharding, substrings, toxicity
from starfold.llm.oracles import ORACLES  # noqa: F401
from starfold.llm.shared import crc_part, documents, table

TOKENIZER = public_tokenizers.path("word_bpe_49k.json")
#: Session setting that holds the key of the pseudonyms; a run without it uses a public value, which hides nothing.
PRIVATE_KEY_SETTING, PUBLIC_KEY = "spark.starfold.pseudonym.key", "public-demonstration"


def private_key(spark) -> str:
    return spark.conf.get(PRIVATE_KEY_SETTING, None) or PUBLIC_KEY


def op1_language_id(spark, sf_dir):
    docs = documents(spark, sf_dir).select("doc_id", "text", "lang")
    net = language.fit(docs.where(crc_part("doc_id", 5) != 0))
    rows = docs.select("doc_id", "text", F.coalesce(crc_part("doc_id", 5) == 0, F.lit(False)).alias("held_out"))
    return language.predict(rows, net, carry=("doc_id", "held_out"))


def op2_toxicity(spark, sf_dir):
    docs = documents(spark, sf_dir).select("doc_id", "text")
    model = toxicity.fit(docs, table(spark, sf_dir, "labels").where(crc_part("doc_id", 3) != 1))
    rows = docs.select("doc_id", "text", F.coalesce(crc_part("doc_id", 3) == 1, F.lit(False)).alias("held_out"))
    return toxicity.score(rows, model, carry=("doc_id", "held_out"))


def op3_decontamination(spark, sf_dir):
    return decontaminate.report(documents(spark, sf_dir), table(spark, sf_dir, "benchmark"))


def op4_packing(spark, sf_dir):
    return packing.pack_documents(documents(spark, sf_dir), TOKENIZER)


def op5_substring_dedup(spark, sf_dir):
    return substrings.removed(documents(spark, sf_dir))


def op6_pseudonyms(spark, sf_dir):
    return private.pseudonymize(documents(spark, sf_dir).select("doc_id", "text"), key=private_key(spark))


def op7_near_duplicates(spark, sf_dir):
    return neardup.classes(documents(spark, sf_dir).select("doc_id", "text"))


def op8_quality(spark, sf_dir):
    return quality.judge(documents(spark, sf_dir))


def op9_sharding(spark, sf_dir):
    return sharding.shard_documents(documents(spark, sf_dir))


def op10_licenses(spark, sf_dir):
    return licenses.scan(documents(spark, sf_dir))


QUERIES = {f.__name__: f for f in (
    op1_language_id, op2_toxicity, op3_decontamination, op4_packing, op5_substring_dedup, op6_pseudonyms,
    op7_near_duplicates, op8_quality, op9_sharding, op10_licenses,
)}
