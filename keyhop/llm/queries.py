"""The queries of this subpackage, with production parameters over whole tables, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from keyhop.runtime import table

WORD_BPE = public_tokenizers.path("word_bpe_49k.json")


def op1_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from keyhop.llm.decontamination import leaks

    return leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from keyhop.llm.token_counts import token_counts

    return token_counts(table(spark, sf_dir, "documents"), WORD_BPE, max_tokens=2048)


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from keyhop.llm.quality_rules import apply_rules

    return apply_rules(table(spark, sf_dir, "documents"))


def op4_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    from keyhop.llm import language_id as li

    docs = table(spark, sf_dir, "documents")
    found = li.identify(docs, li.train(docs.where(~li.held_out())))
    return found.select("doc_id", li.held_out().alias("held_out"), "lang_pred", "score", "mixture")


def op9_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    from keyhop.llm import quality_classifier as qc

    docs = table(spark, sf_dir, "documents")
    model = qc.train(docs, table(spark, sf_dir, "labels"))
    return qc.classify(docs, model).select("doc_id", qc.held_out().alias("held_out"), "score", "predicted")


def op5_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    from keyhop.llm.near_duplicates import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents"), percent=80, width=2)


def op6_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    from keyhop.llm import pii

    docs = table(spark, sf_dir, "documents")
    return pii.find(docs, pii.train(docs))


def op10_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    from keyhop.llm import secrets

    docs = table(spark, sf_dir, "documents")
    return secrets.scan(docs, secrets.train(docs))


def op7_language_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    from keyhop.llm import language_model as lm

    scored = lm.score(table(spark, sf_dir, "documents"), ~lm.held_out())
    return scored.select("doc_id", lm.held_out().alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")


def op8_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from keyhop.llm.packing import pack

    return pack(table(spark, sf_dir, "documents"), WORD_BPE, capacity=4096)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_decontamination": op1_decontamination,
        "op2_token_counts": op2_token_counts,
        "op3_quality_rules": op3_quality_rules,
        "op4_language_id": op4_language_id,
        "op5_near_duplicates": op5_near_duplicates,
        "op6_pii": op6_pii,
        "op10_secrets": op10_secrets,
        "op9_quality_classifier": op9_quality_classifier,
        "op7_language_model": op7_language_model,
        "op8_best_fit_packing": op8_best_fit_packing,
    }


def oracle_sql() -> dict[str, str]:
    return {}
