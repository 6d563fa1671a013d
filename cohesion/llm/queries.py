"""The registered queries of this subpackage: thin wrappers that apply each operator to its whole tables."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from ..session import load_table
from . import decontaminate, fingerprint, language, neardup, packing, pii, quality, secrets, sentencededup, suffixdedup


def op4_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(load_table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))


def op1_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffixdedup.remove_repeats(load_table(spark, sf_dir, "documents"))


def op2_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.scan(load_table(spark, sf_dir, "documents"))


def op3_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint.compare_with_next(load_table(spark, sf_dir, "documents"))


def op5_sentence_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sentencededup.remove_repeats(load_table(spark, sf_dir, "documents"))


def op6_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contamination(load_table(spark, sf_dir, "documents"), load_table(spark, sf_dir, "benchmark"))


def op7_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load_table(spark, sf_dir, "documents")
    return quality.score(docs, quality.fit(docs, load_table(spark, sf_dir, "labels")))


def op8_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_duplicates(load_table(spark, sf_dir, "documents"))


def op9_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load_table(spark, sf_dir, "documents")
    return pii.scan(docs, pii.fit(docs))


def op10_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load_table(spark, sf_dir, "documents")
    model, threshold = language.fit(docs)
    return language.predict(docs, model, threshold)


QUERIES = {f.__name__: f for f in (op1_suffix_dedup, op2_secret_scan, op3_fingerprints, op4_packing, op5_sentence_dedup, op6_decontamination, op7_quality, op8_near_duplicates, op9_personal_data, op10_language)}
ORACLES: dict[str, str] = {"op2_secret_scan": secrets.oracle()}
