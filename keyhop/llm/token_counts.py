"""Token counts by a two-tier lookup on the map side; no pre-token is ever shuffled.

Tier one is a hash table of the corpus's most frequent words (the pre-tokens between two spaces as one
unit, as no pre-token spans white space) with the number of tokens that each takes. The words are
counted in a bounded sample of the texts, which changes nothing but the hit rate; the table has a fixed
number of entries, is built once on the driver and broadcast. Tier two is a cache in each Python
worker, bounded by a number of words, which the library's own merges fill on a miss. One pass over the
whole texts, one row out for each row in, no exchange.
"""

from __future__ import annotations

import heapq
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyhop.llm import bpe
from keyhop.llm.sampling import sample
from keyhop.runtime import ship


def frequent_words(df: DataFrame, rows: int = 4000, entries: int = 30_000, id_col: str = "doc_id", text_col: str = "text") -> list[str]:
    """The most frequent words (at most ``entries``) of a sample of ``rows`` texts, most frequent first."""
    ship(df.sparkSession)
    taken = sample(df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")), "id", rows, "tokens").select("text")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: Counter = Counter()
        for batch in batches:
            for text in batch.column(0):
                held.update(bpe.plain_words(text.as_py()))
        top = heapq.nsmallest(entries, held.items(), key=lambda x: (-x[1], x[0]))
        yield pa.RecordBatch.from_arrays([pa.array([w for w, _ in top], pa.string()), pa.array([n for _, n in top], pa.int64())], ["word", "n"])

    return [r["word"] for r in taken.mapInArrow(count, "word string, n bigint").groupBy("word").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "word").limit(entries).collect()]


def token_counts(df: DataFrame, tokenizer_path: str, max_tokens: int = 2048, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col``, ``n_bytes``, ``n_tokens`` and ``over_limit`` of every row's whole text.

    A null text counts as an empty one: no bytes, no tokens. Rows repeat as they repeat in ``df``; a
    null id is carried. Other columns of ``df`` are not read, whatever their names. Texts are encoded
    whole at any length; an empty table gives an empty result.
    """
    spark = df.sparkSession
    ship(spark)
    frequent = spark.sparkContext.broadcast(bpe.frequent_lengths(tokenizer_path, frequent_words(df, id_col=id_col, text_col=text_col)))
    id_type = df.schema[id_col].dataType.simpleString()

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lengths = bpe.worker_lengths(tokenizer_path, frequent.value)
        for batch in batches:
            texts = batch.column(1)
            n = pa.array([lengths.count(t.as_py()) for t in texts], pa.int64())
            n_bytes = pc.fill_null(pc.cast(pc.binary_length(texts), pa.int64()), 0)
            yield pa.RecordBatch.from_arrays([batch.column(0), n_bytes, n], ["id", "n_bytes", "n_tokens"])

    rows = df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    counted = rows.mapInArrow(count, f"id {id_type}, n_bytes bigint, n_tokens bigint")
    return counted.select(F.col("id").alias(id_col), "n_bytes", "n_tokens", (F.col("n_tokens") > max_tokens).alias("over_limit"))
