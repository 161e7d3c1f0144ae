"""Secret scan: fixed patterns, and two character Markov models compared by log-likelihood ratio.

One model describes random strings, the other ordinary words and identifiers. Both are first-order
chains over ASCII, trained from labelled samples: strings that the fixed patterns catch in the corpus
(and random strings over the usual key alphabets) on one side, the corpus's own words on the other. A
run of at least six key characters, or such a part of it between separators, is a secret when the ratio
is high enough in total and for each character; what has no letter is a number, not a key.
"""

from __future__ import annotations

import hashlib
import heapq
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyhop.llm.sampling import sample
from keyhop.runtime import ship

KINDS = ("assign", "access", "hex")
RANDOM = "random"
#: The fixed patterns of the base.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
#: As in the fixed patterns, a shorter string is no key.
LEAST = 6
#: 0 no key character, 1 a separator of parts (of paths, names and words), 2 any other key character, 3 a letter.
_CLASS = np.zeros(128, np.uint8)
_CLASS[list(b"/-_")] = 1
_CLASS[list(b"0123456789+=")] = 2
_CLASS[list(b"ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz")] = 3
_NAMES = ("passw", "secret", "token", "api")

Span = tuple[int, int, str]


def base_spans(text: str) -> list[Span]:
    """Spans (start, end, kind) of the fixed patterns, whole matches, by start, then kind."""
    out: list[Span] = []
    folded = text.lower()
    if any(n in folded for n in _NAMES):
        out += [(m.start(), m.end(), "assign") for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 6]
    if "AKIA" in text:
        out += [(m.start(), m.end(), "access") for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    out += [(m.start(), m.end(), "hex") for m in HEX.finditer(text)]
    return sorted(out, key=lambda s: (s[0], KINDS.index(s[2])))


def listed(spans: list[Span]) -> str:
    return ",".join(f"{kind}:{start}:{end}" for start, end, kind in spans)


class Ratio:
    """Log-likelihood ratio of random strings against identifiers; positive speaks for random."""

    def __init__(self, table: np.ndarray, total: float, each: float):
        self.table, self.total, self.each = table, total, each

    @staticmethod
    def chain(strings: list[str], smoothing: float = 0.3) -> np.ndarray:
        """Log transition probabilities; row 0 stands for the start."""
        counts = np.full((128, 128), smoothing)
        for s in strings:
            code = np.frombuffer(b"\0" + s.encode("ascii", "ignore"), np.uint8)
            np.add.at(counts, (code[:-1], code[1:]), 1)
        return np.log(counts / counts.sum(axis=1, keepdims=True))

    @classmethod
    def fit(cls, random: list[str], words: list[str], total: float = 6.0, each: float = 0.45) -> Ratio:
        """Train both chains; key alphabets are filled up with generated strings, words with their capitals."""
        rng = np.random.default_rng(11)
        alphabets = ("0123456789abcdef", "ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/")
        made = ["".join(rng.choice(list(a), 40)) for a in alphabets for _ in range(500)]
        common = ("user_id", "get_value", "camelCaseName", "HttpResponseCode", "max-retry-count", "x86_64", "utf8", "sha256", "index_2024_01", "README", "version2", "/usr/local/lib/python3", "path/to/some/file", "com_example_project", "getElementById", "isAuthenticatedUser")
        plain = [*words, *(w.upper() for w in words[::3]), *(w.capitalize() for w in words[::3]), *common * max(1, len(words) // 200)]
        joined = [f"{a}{sep}{b}" for sep in "_-/" for a, b in zip(plain[::9], plain[4::9], strict=False)]
        table = cls.chain([*random, *made]) - cls.chain([*plain, *joined])
        return cls(table, total, each)

    def score(self, s: str) -> float:
        code = np.frombuffer(b"\0" + s.encode("ascii", "ignore"), np.uint8)
        return float(self.table[code[:-1], code[1:]].sum())

    def is_random(self, s: str) -> bool:
        """At least ``LEAST`` characters with a letter, and a ratio above both limits."""
        ratio = self.score(s)
        return len(s) >= LEAST and any(map(str.isalpha, s)) and ratio > self.total and ratio > self.each * len(s)

    def random_runs(self, code: np.ndarray, inside: np.ndarray, letters: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Starts and ends of the maximal runs of ``inside``, and which of them are random."""
        edge = np.flatnonzero(np.diff(inside.astype(np.int8), prepend=0, append=0))
        start, end = edge[::2], edge[1::2]
        before = np.zeros(len(code), np.uint8)
        before[1:] = code[:-1]
        before[start] = 0
        sums = np.concatenate(([0.0], np.cumsum(np.where(inside, self.table[before, code], 0))))
        ratio = sums[end] - sums[start]
        return start, end, (end - start >= LEAST) & (letters[end] > letters[start]) & (ratio > self.total) & (ratio > self.each * (end - start))

    def spans(self, text: str, base: list[Span]) -> list[Span]:
        """Random runs, and random parts of other runs, that touch no base span."""
        if not text:
            return []
        wide = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
        code = np.where(wide < 128, wide, 0).astype(np.uint8)
        kind = _CLASS[code]
        letters = np.concatenate(([0], np.cumsum(kind == 3)))
        change = np.zeros(len(code) + 1, np.int64)  # +1 where a taken span starts, -1 where it ends
        np.add.at(change, [a for a, _, _ in base], 1)
        np.add.at(change, [b for _, b, _ in base], -1)
        out: list[Span] = []
        for least in (1, 2):
            taken = np.concatenate(([0], np.cumsum(np.cumsum(change[:-1]) > 0)))
            start, end, found = self.random_runs(code, kind >= least, letters)
            found &= taken[end] == taken[start]
            out += [(a, b, RANDOM) for a, b in zip(start[found].tolist(), end[found].tolist(), strict=True)]
            np.add.at(change, start[found], 1)
            np.add.at(change, end[found], -1)
        return sorted(out)


def train(df: DataFrame, rows: int = 3000, words_per_task: int = 3000, id_col: str = "doc_id", text_col: str = "text") -> Ratio:
    """Fit on up to ``rows`` rows of ``df``; each of 8 tasks gives up to ``words_per_task`` strings of either label."""
    ship(df.sparkSession)
    taken = sample(df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")), "id", rows, "secrets").select("text").where("text is not null")

    def label(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[bool, set[str]] = {True: set(), False: set()}
        for batch in batches:
            for text in batch.column(0).to_pylist():
                base = base_spans(text)
                held[True].update(re.split(r"[:=\"' ]", text[a:b])[-1] for a, b, _ in base)
                held[False].update(w for w in re.findall(r"(?<!\S)[A-Za-z]{2,40}(?!\S)", text))
                held = {k: set(heapq.nsmallest(words_per_task, v, key=lambda w: (zlib.crc32(w.encode()), w))) if len(v) > 4 * words_per_task else v for k, v in held.items()}
        kept = [(k, w) for k, v in held.items() for w in heapq.nsmallest(words_per_task, v, key=lambda w: (zlib.crc32(w.encode()), w))]
        yield pa.RecordBatch.from_arrays([pa.array([k for k, _ in kept], pa.bool_()), pa.array([w for _, w in kept], pa.string())], ["secret", "string"])

    found = taken.repartition(8).mapInArrow(label, "secret boolean, string string").collect()
    by = {k: sorted({r["string"] for r in found if r["secret"] is k}) for k in (True, False)}
    return Ratio.fit(by[True], by[False])


def scan(df: DataFrame, model: Ratio, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col``, ``n_assign``, ``n_access``, ``n_hex`` (base spans), ``base_sha256`` and ``spans`` of every whole text.

    A null text is an empty one, with no span. Spans are code points, end exclusive; a ``random`` span
    is one that the Markov models add. Texts are scanned whole, in time linear in their length. Repeated
    rows get equal answers, a null id is carried, an empty table gives an empty result; other columns
    aren't read, whatever their names.
    """
    spark = df.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(model)
    id_type = df.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ratio = shared.value
        order = {k: i for i, k in enumerate((*KINDS, RANDOM))}
        for batch in batches:
            counts: dict[str, list[int]] = {k: [] for k in KINDS}
            digests, spans = [], []
            for value in batch.column(1):
                text = value.as_py() or ""
                base = base_spans(text)
                for k in KINDS:
                    counts[k].append(sum(s[2] == k for s in base))
                digests.append(hashlib.sha256(listed(base).encode()).hexdigest())
                spans.append(listed(sorted([*base, *ratio.spans(text, base)], key=lambda s: (s[0], order[s[2]]))))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), *(pa.array(counts[k], pa.int64()) for k in KINDS), pa.array(digests, pa.string()), pa.array(spans, pa.string())], ["id", *(f"n_{k}" for k in KINDS), "base_sha256", "spans"]
            )

    rows = df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(run, f"id {id_type}, n_assign bigint, n_access bigint, n_hex bigint, base_sha256 string, spans string").withColumnRenamed("id", id_col)
