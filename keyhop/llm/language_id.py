"""Language identification as inference of a mixture of languages.

Every language has a distribution over hashed character trigrams. A document is taken as a mixture of
some of these languages in unknown proportions, which expectation-maximisation estimates from the
likelihoods of its trigrams. Which languages take part is decided by penalised likelihood: starting
with the best single language, the language whose addition promises most (by the slope of the
likelihood) is added as long as the likelihood gained exceeds the penalty.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from keyhop.llm.sampling import crc_mod, hash_share
from keyhop.runtime import ship

BUCKETS = 1 << 15
UNKNOWN = "und"
_WORKER: dict = {}


def _letters() -> np.ndarray:
    """Which code points are letters; made once per process."""
    if "letters" not in _WORKER:
        _WORKER["letters"] = np.fromiter((chr(c).isalpha() for c in range(0x110000)), bool, 0x110000)
    return _WORKER["letters"]


def trigram_counts(text: str | None) -> np.ndarray | None:
    """Counts by bucket of the trigrams of letters (runs of anything else are one gap); None without letters."""
    if not text:
        return None
    code = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)
    is_letter = _letters()[code]
    if not is_letter.any():
        return None
    code = np.where(is_letter, code, 32).astype(np.uint64)
    keep = np.ones(len(code), bool)
    keep[1:] = is_letter[1:] | is_letter[:-1]
    code = np.concatenate(([32], code[keep], [32])).astype(np.uint64)
    mixed = code[:-2] * np.uint64(0x9E3779B97F4A7C15) + code[1:-1] * np.uint64(0xC2B2AE3D27D4EB4F) + code[2:] * np.uint64(0x165667B19E3779F9)
    mixed ^= mixed >> np.uint64(29)
    mixed *= np.uint64(0xBF58476D1CE4E5B9)
    return np.bincount((mixed >> np.uint64(49)).astype(np.int64), minlength=BUCKETS)


class Mixture:
    """Languages and the log-probabilities of their buckets."""

    def __init__(self, counts: dict[str, np.ndarray], smoothing: float = 0.5, penalty: float = 2.0, rounds: int = 50):
        self.langs = sorted(counts)
        self.penalty, self.rounds = penalty, rounds
        raw = np.array([counts[x] for x in self.langs], np.float64).reshape(len(self.langs), BUCKETS) + smoothing
        self.prob = np.ascontiguousarray((raw / raw.sum(axis=1, keepdims=True)).T)
        self.log = np.log(self.prob)

    def _em(self, n: np.ndarray, p: np.ndarray, share: np.ndarray) -> tuple[np.ndarray, float]:
        total = n.sum()
        for _ in range(self.rounds):
            each = p * share
            new = (n / each.sum(axis=1)) @ each / total
            done = np.abs(new - share).max() < 1e-4
            share = new
            if done:
                break
        return share, float(n @ np.log(p @ share))

    def infer(self, counts: np.ndarray) -> list[tuple[str, float]]:
        """The chosen languages with their proportions, largest first; ties go to the smaller name."""
        at = np.flatnonzero(counts)
        n = counts[at].astype(np.float64)
        single = n @ self.log[at]
        chosen = [int(single.argmax())]
        share, like = np.ones(1), float(single.max())
        cost = self.penalty * np.log(n.sum() + 1)
        p = self.prob[at]
        while len(chosen) < len(self.langs):
            slope = (n / (p[:, chosen] @ share)) @ p - n.sum()
            slope[chosen] = -np.inf
            best = int(slope.argmax())
            if slope[best] <= cost:  # the likelihood is concave in the shares: no larger gain is possible
                break
            share2, like2 = self._em(n, p[:, [*chosen, best]], np.append(share * 0.9, 0.1))
            if like2 - like <= cost:
                break
            chosen, share, like = [*chosen, best], share2, like2
        return sorted(((self.langs[c], float(s)) for c, s in zip(chosen, share, strict=True)), key=lambda x: (-x[1], x[0]))


def train(df: DataFrame, rows_per_language: int = 1500, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", **options) -> Mixture:
    """Fit the trigram distributions on up to ``rows_per_language`` rows of each language of ``df``."""
    labelled = df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"), F.col(lang_col).alias("lang")).where("lang is not null")
    sizes = {r["lang"]: r["n"] for r in labelled.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}
    if not sizes:
        return Mixture({})
    ship(df.sparkSession)
    limit = F.create_map(*[x for k, n in sizes.items() for x in (F.lit(k), F.lit(int((1 << 32) * min(1.0, rows_per_language / n))))])
    taken = labelled.where(hash_share(F.col("id"), "language") < F.element_at(limit, F.col("lang")))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, np.ndarray] = {}
        for batch in batches:
            for text, lang in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                if (c := trigram_counts(text)) is not None:
                    held[lang] = held[lang] + c if lang in held else c
        yield pa.RecordBatch.from_arrays([pa.array(held, pa.string()), pa.array([c.astype(np.int64).tobytes() for c in held.values()], pa.binary())], ["lang", "counts"])

    total = {k: np.zeros(BUCKETS, np.int64) for k in sizes}
    for r in taken.repartition(8).mapInArrow(count, "lang string, counts binary").collect():  # 8 tasks, one array per language
        total[r["lang"]] += np.frombuffer(r["counts"], np.int64)
    return Mixture(total, **options)


def identify(df: DataFrame, model: Mixture, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col``, ``lang_pred``, ``score`` (the proportion of that language) and ``mixture`` of every whole text.

    ``und`` with score 0 stands for a null text, a text without letters, or a model without languages.
    Repeated rows are answered alike; an empty table gives an empty result; other columns aren't read.
    """
    spark = df.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(model)
    id_type = df.schema[id_col].dataType.simpleString()

    def infer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mixture = shared.value
        for batch in batches:
            out = []
            for text in batch.column(1):
                counts = trigram_counts(text.as_py()) if mixture.langs else None
                out.append([(UNKNOWN, 0.0)] if counts is None else mixture.infer(counts))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array([x[0][0] for x in out], pa.string()), pa.array([min(1.0, x[0][1]) for x in out], pa.float64()), pa.array([",".join(f"{k}:{s:.4f}" for k, s in x) for x in out], pa.string())],
                ["id", "lang_pred", "score", "mixture"],
            )

    rows = df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(infer, f"id {id_type}, lang_pred string, score double, mixture string").withColumnRenamed("id", id_col)


def held_out(id_col: str = "doc_id") -> Column:
    """The rows that training must not see."""
    return F.coalesce(crc_mod(F.col(id_col), 3) == 1, F.lit(False))
