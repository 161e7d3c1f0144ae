"""Quality classifier: a factorisation machine over hashed words, structure statistics and metadata.

The score is a bias, a linear term and all pairwise interactions, whose weights are inner products of
short factor vectors. The pair term costs time linear in the features: for each factor, half of the
square of the sum less the sum of the squares.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from keyhop.llm.sampling import crc_mod, sample
from keyhop.runtime import ship

WORDS = 1 << 13
BINS = 12
STATS = ("log_chars", "log_words", "word_chars", "symbols", "capitals", "digits", "distinct", "repeated_lines", "sentence_ends", "long_words", "bangs", "line_words")
SIZE = WORDS + BINS * len(STATS)
_SYMBOLS = frozenset("#*$%&|<>{}[]\\^~@=+/_")


def features(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """Feature numbers and values of a whole text; a null text counts as empty."""
    text = text or ""
    words = text.split()
    n, chars = len(words), len(text)
    seen = set(words)
    hashed = np.fromiter((zlib.crc32(w.encode("utf-8", "surrogatepass")) for w in seen), np.int64, len(seen)) & (WORDS - 1)
    hashed = np.unique(hashed)
    lines = [x for x in text.split("\n") if x]
    per_char = 1 / max(chars, 1)
    upper = sum(map(str.isupper, seen))
    stats = (
        np.log1p(chars) / 12,
        np.log1p(n) / 10,
        chars / max(n, 1) / 20,
        sum(map(text.count, _SYMBOLS)) * per_char * 5,
        upper / max(len(seen), 1),
        sum(map(text.count, "0123456789")) * per_char * 5,
        len(seen) / max(n, 1),
        1 - len(set(lines)) / max(len(lines), 1),
        (text.count(".") + text.count("?")) / max(n, 1) * 4,
        sum(len(w) > 14 for w in seen) / max(len(seen), 1),
        text.count("!") / max(n, 1),
        np.log1p(n / max(len(lines), 1)) / 6,
    )
    bins = np.minimum((np.clip(stats, 0, 1) * BINS).astype(np.int64), BINS - 1) + np.arange(len(STATS)) * BINS + WORDS
    values = np.concatenate((np.full(len(hashed), 1 / np.sqrt(max(len(hashed), 1))), np.full(len(bins), 0.5)))
    return np.concatenate((hashed, bins)), values


class FactorisationMachine:
    """Weights: ``bias``, ``linear`` by feature and ``factors`` by feature and factor."""

    def __init__(self, factors: int = 8, seed: int = 7):
        self.bias = 0.0
        self.linear = np.zeros(SIZE)
        self.factors = np.random.default_rng(seed).normal(0, 0.02, (SIZE, factors))

    def raw(self, at: np.ndarray, x: np.ndarray) -> float:
        vx = self.factors[at] * x[:, None]
        total = vx.sum(axis=0)
        return float(self.bias + self.linear[at] @ x + 0.5 * (total @ total - (vx * vx).sum()))

    def score(self, text: str | None) -> float:
        return float(1 / (1 + np.exp(-np.clip(self.raw(*features(text)), -35, 35))))

    def fit(self, rows: list[tuple[np.ndarray, np.ndarray]], labels: np.ndarray, epochs: int = 12, rate: float = 0.1, decay: float = 1e-5, seed: int = 7) -> FactorisationMachine:
        """AdaGrad on the logistic loss, one row at a time."""
        if not len(labels):
            return self
        share = min(max(labels.mean(), 0.01), 0.99)
        self.bias = float(np.log(share / (1 - share)))
        g0, g1, g2 = 1e-2, np.full(SIZE, 1e-2), np.full(self.factors.shape, 1e-2)
        rng = np.random.default_rng(seed)
        for _ in range(epochs):
            for i in rng.permutation(len(rows)):
                at, x = rows[i]
                v = self.factors[at]
                vx = v * x[:, None]
                total = vx.sum(axis=0)
                raw = self.bias + self.linear[at] @ x + 0.5 * (total @ total - (vx * vx).sum())
                err = 1 / (1 + np.exp(-np.clip(raw, -35, 35))) - labels[i]
                if abs(err) < 1e-3:
                    continue
                g0 += err * err
                self.bias -= rate * err / np.sqrt(g0)
                d = err * x + decay * self.linear[at]
                g1[at] += d * d
                self.linear[at] -= rate * d / np.sqrt(g1[at])
                d = err * x[:, None] * (total - vx) + decay * v
                g2[at] += d * d
                self.factors[at] = v - rate * 0.3 * d / np.sqrt(g2[at])
        return self


def train(docs: DataFrame, labels: DataFrame, label_col: str = "quality", rows: int = 6000, id_col: str = "doc_id", text_col: str = "text", held_out_mod: int = 5) -> FactorisationMachine:
    """Fit on up to ``rows`` labelled rows, none of whose id hashes to 0 modulo ``held_out_mod``.

    Rows without a label, an id or a text row are not learned from; an id with several labels counts
    with its largest. The chosen labels (at most ``rows``) are broadcast to the documents.
    """
    spark = docs.sparkSession
    ship(spark)
    known = labels.select(F.col(id_col).alias("id"), F.col(label_col).cast("int").alias("label")).where("id is not null and label is not null").where(crc_mod(F.col("id"), held_out_mod) != 0)
    chosen = sample(known, "id", rows, "quality").groupBy("id").agg(F.max("label").alias("label"))
    texts = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")).join(F.broadcast(chosen), "id").select("id", "text", "label")

    def extract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [features(t.as_py()) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array([a.astype(np.int32).tobytes() for a, _ in found], pa.binary()), pa.array([x.tobytes() for _, x in found], pa.binary())], ["id", "label", "at", "x"])

    id_type = docs.schema[id_col].dataType.simpleString()
    got = texts.mapInArrow(extract, f"id {id_type}, label int, at binary, x binary").limit(2 * rows).collect()
    got.sort(key=lambda r: (r["id"], r["at"]))
    pairs = [(np.frombuffer(r["at"], np.int32).astype(np.int64), np.frombuffer(r["x"])) for r in got]
    return FactorisationMachine().fit(pairs, np.array([float(r["label"] > 0) for r in got]))


def classify(df: DataFrame, model: FactorisationMachine, threshold: float = 0.3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col``, ``score`` (0 to 1, higher: label 1 likelier) and ``predicted`` of every whole text.

    A null text is scored as an empty one. Repeated rows get the same score; an empty table gives an
    empty result; other columns are not read.
    """
    spark = df.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(model)
    id_type = df.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        score = shared.value.score
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([score(t.as_py()) for t in batch.column(1)], pa.float64())], ["id", "score"])

    rows = df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(run, f"id {id_type}, score double").select(F.col("id").alias(id_col), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def predict_column(df: DataFrame, model: FactorisationMachine, threshold: float = 0.3, text_col: str = "text") -> DataFrame:
    """``df`` with columns ``score`` and ``predicted`` of its texts added (any of these names is replaced)."""
    ship(df.sparkSession)
    shared = df.sparkSession.sparkContext.broadcast(model)

    @F.arrow_udf("double")
    def scored(texts: pa.Array) -> pa.Array:
        score = shared.value.score
        return pa.array([score(t.as_py()) for t in texts], pa.float64())

    return df.withColumn("score", scored(F.col(text_col).cast("string"))).withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def held_out(id_col: str = "doc_id") -> Column:
    """The rows that training must not see."""
    return F.coalesce(crc_mod(F.col(id_col), 5) == 0, F.lit(False))
