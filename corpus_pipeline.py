"""A training corpus from raw documents: quality, near-duplicates, benchmark leaks, personal data, packing.

Each stage takes what the one before kept, texts whole at any length. All but the last return the columns
of ``documents``; further columns of the input, whatever their names, are not returned.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from keyhop.llm import decontamination, near_duplicates, packing, pii, quality_classifier
from keyhop.runtime import Scratch, table

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
WORD_BPE = public_tokenizers.path("word_bpe_49k.json")


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops the documents that the factorisation machine rejects.

    A null or empty text is judged as an empty one. Rows of one id are judged each by its text. Without
    labels nothing is learned and all documents score alike. An empty table stays empty.
    """
    model = quality_classifier.train(docs, table(spark, sf_dir, "labels"))
    kept = quality_classifier.predict_column(docs, model)
    return kept.where("predicted = 1").select(*COLUMNS)


def deduplicate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Leaves one document of each group of near-duplicates (five-word shingles, similarity 0.8).

    Null and empty texts are in no group and stay. Rows of one id stay or go together; rows without an
    id stay. An empty table stays empty.
    """
    return near_duplicates.keep_one(docs, percent=80, width=5).select(*COLUMNS)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops the documents that hold a benchmark item.

    Null and empty texts hold none. Rows of one id, null included, stay or go together. An empty table
    stays empty, and an empty benchmark drops nothing.
    """
    return decontamination.decontaminate(docs, table(spark, sf_dir, "benchmark")).select(*COLUMNS)


def mask_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replaces personal data by its kind, and counts the characters anew.

    All rows stay, repeated ones and those without an id too; a null text stays null and keeps its
    count. An empty table stays empty.
    """
    masked = pii.masked_column(docs, pii.train(docs))
    return masked.withColumn("n_chars", F.when(F.col("text").isNotNull(), F.length("text").cast("bigint")).otherwise(F.col("n_chars"))).select(*COLUMNS)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs all documents into sequences of at most 4096 tokens.

    A null or empty text is the closing token alone. Rows of one id are packed one by one. An empty
    table gives no pieces.
    """
    return packing.pack(docs, WORD_BPE, capacity=4096)


STAGES = [
    ("quality_classifier", quality),
    ("near_duplicates", deduplicate),
    ("decontamination", decontaminate),
    ("pii", mask_personal_data),
    ("packing", pack),
]

#: The learned stages have no SQL; tests hold the result against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written to the shared folder and read again."""
    scratch = Scratch(spark, "pipeline")
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = scratch.save(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)


def queries() -> dict:
    return {"pipeline": run}


def oracle_sql() -> dict[str, str]:
    return {}
