"""The registered queries ``opN_<name>``, with production parameters over whole tables, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from coreshell.llm import bpe_counts, budget_mix, credentials, dart_minhash, decontaminate, fingerprints, line_templates, lm_difference, repair_store, toxicity
from coreshell.llm.shared import documents


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_line_templates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_templates.drop_recurring(documents(spark, sf_dir))


def op2_lm_difference(spark: SparkSession, sf_dir: str) -> DataFrame:
    good = table(spark, sf_dir, "labels").where("quality = 1")
    return lm_difference.score(documents(spark, sf_dir), good)


def op3_canonical_digest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints.edited(documents(spark, sf_dir))


def op4_credential_linking(spark: SparkSession, sf_dir: str) -> DataFrame:
    return credentials.scan(documents(spark, sf_dir))


def op5_dart_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dart_minhash.near_duplicates(documents(spark, sf_dir))


def op6_sentence_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    return toxicity.score(docs, toxicity.train(docs, table(spark, sf_dir, "labels")))


def op7_budget_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return budget_mix.mix(documents(spark, sf_dir))


def op8_benchmark_leaks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.leaks(documents(spark, sf_dir), table(spark, sf_dir, "benchmark"))


def op9_grammar_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    shards, first_rule = repair_store.write_ids(documents(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.json"))
    return repair_store.read_documents(shards, first_rule)


def op10_bpe_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe_counts.count_tokens(documents(spark, sf_dir), public_tokenizers.path("word_bpe_49k.json"))


QUERIES = (op1_line_templates, op2_lm_difference, op3_canonical_digest, op4_credential_linking, op5_dart_minhash, op6_sentence_toxicity, op7_budget_mix, op8_benchmark_leaks, op9_grammar_ids, op10_bpe_counts)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in QUERIES}


def oracle_sql() -> dict[str, str]:
    """SQL where it can express an operator; the others are tested against brute force, round trips or held-out labels."""
    return {"op1_line_templates": line_templates.ORACLE_SQL}
