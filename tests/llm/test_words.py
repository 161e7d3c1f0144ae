import os
import random

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from keyhop.llm import language_model
from keyhop.llm.near_duplicates import folded_words
from keyhop.runtime import Scratch, table


def test_words_and_hashes_equal_those_of_spark(spark, texts, monkeypatch):
    words = pytest.importorskip("keyhop.llm.words")
    rng = random.Random(1)
    texts = [t or "" for t in texts] + [" ".join("".join(rng.choice("aBZcÉdé€𝒳\x1c") for _ in range(rng.randint(1, 80))) for _ in range(20)) for _ in range(40)] + ["", " "]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "i int, t string").select("i", folded_words(F.col("t")).alias("w"))
    rows = df.select("w", F.transform("w", lambda w: F.xxhash64(w)).alias("h"), "i").orderBy("i").collect()
    column = pa.array(["left out", *texts]).slice(1)
    for size in (1, 3000, 1 << 20):
        monkeypatch.setattr(words, "PART", size)
        got = list(words.parts(column))
        assert [a for a, _, _ in got] == [0, *(b for _, b, _ in got[:-1])] and got[-1][1] == len(texts)
        assert [n for _, _, g in got for n in g.count.tolist()] == [len(r["w"]) for r in rows]
        assert [x for _, _, g in got for x in g.strings(np.arange(len(g.start))).to_pylist()] == [x for r in rows for x in r["w"]]
        assert [x for _, _, g in got for x in g.hash.tolist()] == [x for r in rows for x in r["h"]]


def test_packed_columns_come_back():
    words = pytest.importorskip("keyhop.llm.words")
    columns = [np.array([5, -3, 2**62, -(2**63), 2**63 - 1]), np.arange(1000), np.zeros(0, np.int64)]
    back = words.unpack(words.pack(*columns), 3)
    assert all(np.array_equal(a, b) for a, b in zip(columns, back, strict=True))
    assert len(words.pack(np.arange(100_000))) < 1000


def _size(folder):
    return sum(os.path.getsize(os.path.join(d, f)) for d, _, files in os.walk(folder) for f in files if f.endswith(".parquet"))


def test_language_model_keeps_pairs_in_few_bytes(spark, sf):
    """Pairs with their rows, and the vocabulary: less than half of two hashes and two numbers for each pair."""
    scratch = Scratch(spark, "size")
    scored, _ = language_model.train(table(spark, sf, "documents").withColumn("words", folded_words(F.col("text"))).withColumn("h", language_model.hashed(F.col("words"))), ~language_model.held_out(), scratch)
    taken = _size(scratch.root.removeprefix("file:"))
    print(taken, scored.count())
    assert 0 < taken < 20 * scored.count()


def test_language_model_scores_do_not_depend_on_what_is_frequent(spark, sf):
    """Nor on the number of tasks that pairs are dealt to: rare words take another way to the same scores."""
    d = table(spark, sf, "documents").limit(120)
    plain, other = ({r["doc_id"]: r for r in language_model.score(d, ~language_model.held_out(), **options).collect()} for options in ({}, {"frequent": 50, "pairs": 5000}))
    assert plain.keys() == other.keys() and len(plain) == 120
    for i, r in plain.items():
        assert (r["n_tokens"], r["n_known"]) == (other[i]["n_tokens"], other[i]["n_known"])
        assert np.allclose([r["score"], r["base_score"]], [other[i]["score"], other[i]["base_score"]], rtol=1e-9)
