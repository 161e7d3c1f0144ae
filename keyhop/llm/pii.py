"""Personal data: fixed patterns, and a semi-Markov conditional random field that adds spans.

The field scores whole candidate segments of up to ``LONGEST`` tokens by features of the span: its
groups of digits, separators, checksums, what stands around it. A dynamic programme over the tokens
chooses boundaries and types jointly; training maximises the conditional likelihood of the labelled
segmentation, with expectations from the same lattice.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_left
from collections.abc import Iterator
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyhop.llm.sampling import hash_share, sample
from keyhop.runtime import ship

KINDS = ("email", "ip", "card", "phone")
LONGEST = 16
#: The fixed patterns of the base.
IP = re.compile(r"(?<![0-9])[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
DOMAIN = re.compile(r"[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DIGIT = re.compile(r"[0-9]")
#: Without one of these no candidate segment exists.
TRIGGER = re.compile(r"[0-9@]|[\[(] ?at ?[\])]")
TOKEN = re.compile(r"[0-9]+|[^\W\d_]+|[^\s\w]|_|\S")

Span = tuple[str, int, int]


def luhn(digits: str) -> bool:
    """Whether the digits' checksum is right."""
    total = 0
    for i, d in enumerate(reversed(digits)):
        x = int(d) * (1 + i % 2)
        total += x - 9 if x > 9 else x
    return total % 10 == 0


def _emails(text: str) -> Iterator[Span]:
    """Leftmost matches, found from each @ outward: linear also in long runs of address characters."""
    done, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in _LOCAL:
            start -= 1
        host = DOMAIN.match(text, at + 1) if start < at else None
        if host:
            yield "email", start, host.end()
            done = host.end()
        at = text.find("@", max(done, at + 1))


def _digits(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def base_spans(text: str) -> list[Span]:
    """Spans (kind, start, end) of the fixed patterns by kind, then start; failing matches are dropped."""
    out = list(_emails(text))
    if _DIGIT.search(text):
        out += [("ip", *m.span()) for m in IP.finditer(text) if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m.group().split("."))]
        out += [("card", *m.span()) for m in CARD.finditer(text) if 16 <= len(d := _digits(m.group())) <= 19 and luhn(d)]
        if "+" in text:
            out += [("phone", *m.span()) for m in PHONE.finditer(text) if 8 <= len(_digits(m.group())) <= 15]
    return out


def listed(spans: list[Span]) -> str:
    return ",".join(f"{kind}:{start}:{end}" for kind, start, end in spans)


class Lattice:
    """The candidate segments of a text: tokens, and for each end token the possible starts."""

    def __init__(self, text: str):
        self.text = text
        self.tokens = [m.span() for m in TOKEN.finditer(text)] if TRIGGER.search(text) else []

    def segments(self) -> Iterator[tuple[int, int]]:
        """Pairs of first and last token whose span may be personal data, by last, then first token.

        A span starts with a letter, digit, + or opening bracket, ends with a letter or digit, has no
        break wider than one space, holds a digit, and either only digits and the separators of
        numbers, or letters around one at-sign.
        """
        text, tokens = self.text, self.tokens
        n = len(tokens)
        kind = []
        for a, _ in tokens:
            c = text[a]
            kind.append("d" if "0" <= c <= "9" else "a" if c.isalpha() else c)
        for last in range(n):
            if kind[last] not in "da":
                continue
            digits = letters = ats = False
            spaced = 0
            for first in range(last, max(-1, last - LONGEST), -1):
                k = kind[first]
                if first < last:
                    gap = tokens[first + 1][0] - tokens[first][1]
                    if gap > 1 or (gap and text[tokens[first][1]] != " "):
                        break
                    spaced += gap
                if k == "d":
                    digits = True
                elif k == "a":
                    letters = True
                    word = text[tokens[first][0] : tokens[first][1]]
                    ats = ats or (word == "at" and first > 0 and kind[first - 1] in "[(")
                elif k == "@" or (k in ")]" and first > 1 and kind[first - 2] in "[(" and text[slice(*tokens[first - 1])] == "at"):
                    ats = True
                elif k not in "+().-_%[]":
                    break
                if letters and spaced and not ats and first < last:
                    break
                if k in "da+(" and ((digits and not letters) or ats):
                    yield first, last

    def features(self, first: int, last: int) -> list[str]:
        """What the span as a whole and its surroundings look like."""
        text, tokens = self.text, self.tokens
        a, b = tokens[first][0], tokens[last][1]
        s = text[a:b]
        digits = _digits(s)
        groups = re.findall(r"[0-9]+", s)
        before, after = text[a - 1 : a], text[b : b + 1]
        left = text[tokens[first - 1][0] : tokens[first - 1][1]].lower() if first else ""
        out = [
            "bias",
            f"digits={min(len(digits), 20)}",
            f"groups={min(len(groups), 7)}",
            "shape=" + re.sub(r"[A-Za-zÀ-ÿ]+", "a", re.sub(r"[0-9]+", lambda m: f"d{min(len(m.group()), 5)}", s))[:40],
            f"seps={''.join(sorted(set(re.sub(r'[0-9A-Za-zÀ-ÿ]', '', s))))[:6]}",
            f"open={s[0] if s[0] in '+(' else 'x'}",
            f"glued={bool(before.strip() and (before.isalnum() or before in '.-+@'))}{bool(after.strip() and (after.isalnum() or after in '-@'))}",
        ]
        if re.search(r"[a-z]", s, re.IGNORECASE):
            host = re.split(r"@|[\[(] ?at ?[\])]", s)[-1]
            out += ["at", f"host={bool(re.search(r'[.][A-Za-z]{2,}$', host))}", f"local={bool(re.match(r'[A-Za-z0-9._%+-]+ ?[@(\[]', s))}"]
        else:
            out += [f"luhn={len(digits) >= 13 and luhn(digits)}{len(digits) // 4}", f"octets={len(groups) == 4 and s.count('.') == 3 and all(len(g) <= 3 and int(g) <= 255 for g in groups)}"]
        if left in ("tel", "phone", "call", "fax", "mobile", "card", "visa", "ip", "host", "mail", "email"):
            out.append(f"cue={left}")
        return out


class SemiMarkovField:
    """Weights of (feature, kind); the outside costs nothing."""

    def __init__(self, index: dict[str, int] | None = None, weights: np.ndarray | None = None):
        self.index = index or {}
        self.weights = weights if weights is not None else np.zeros((0, len(KINDS)))

    def _scores(self, lattice: Lattice) -> dict[int, list[tuple[int, np.ndarray, list[int]]]]:
        out: dict[int, list[tuple[int, np.ndarray, list[int]]]] = {}
        for first, last in lattice.segments():
            at = [self.index[f] for f in lattice.features(first, last) if f in self.index]
            out.setdefault(last, []).append((first, self.weights[at].sum(axis=0), at))
        return out

    def decode(self, text: str) -> list[Span]:
        """The best segmentation's spans, by start."""
        lattice = Lattice(text)
        if not lattice.tokens or not (ends := self._scores(lattice)):
            return []
        n = len(lattice.tokens)
        best, back = np.zeros(n + 1), [None] * (n + 1)
        for last in range(n):
            best[last + 1] = best[last]
            for first, w, _ in ends.get(last, ()):
                k = int(w.argmax())
                if (v := best[first] + w[k]) > best[last + 1]:
                    best[last + 1], back[last + 1] = v, (first, k)
        out, j = [], n
        while j:
            if back[j]:
                first, k = back[j]
                out.append((KINDS[k], lattice.tokens[first][0], lattice.tokens[j - 1][1]))
                j = first
            else:
                j -= 1
        return out[::-1]

    @classmethod
    def fit(cls, rows: list[tuple[str, list[Span]]], epochs: int = 12, rate: float = 0.5, decay: float = 1e-3) -> SemiMarkovField:
        """Maximise the conditional likelihood of labelled texts by AdaGrad; labels that are no candidates are left out."""
        index: dict[str, int] = {}
        data = []
        for text, spans in rows:
            lattice = Lattice(text)
            gold = {(a, b): KINDS.index(k) for k, a, b in spans}
            segments = []
            for first, last in lattice.segments():
                at = [index.setdefault(f, len(index)) for f in lattice.features(first, last)]
                segments.append((first, last, np.array(at), gold.get((lattice.tokens[first][0], lattice.tokens[last][1]), -1)))
            if segments:
                data.append((len(lattice.tokens), segments))
        field = cls(index, np.zeros((len(index), len(KINDS))))
        squares = np.full(field.weights.shape, 1e-2)
        rng = np.random.default_rng(5)
        for _ in range(epochs):
            for i in rng.permutation(len(data)):
                n, segments = data[i]
                scores = [field.weights[at].sum(axis=0) for _, _, at, _ in segments]
                forward, backward = np.full(n + 1, -np.inf), np.full(n + 1, -np.inf)
                forward[0] = backward[n] = 0.0
                by_end: dict[int, list[int]] = {}
                by_start: dict[int, list[int]] = {}
                for k, (first, last, _, _) in enumerate(segments):
                    by_end.setdefault(last + 1, []).append(k)
                    by_start.setdefault(first, []).append(k)
                for j in range(1, n + 1):
                    forward[j] = np.logaddexp.reduce([forward[j - 1], *(forward[segments[k][0]] + v for k in by_end.get(j, ()) for v in scores[k])])
                for j in range(n - 1, -1, -1):
                    backward[j] = np.logaddexp.reduce([backward[j + 1], *(backward[segments[k][1] + 1] + v for k in by_start.get(j, ()) for v in scores[k])])
                for k, (first, last, at, label) in enumerate(segments):
                    slope = -np.exp(forward[first] + scores[k] + backward[last + 1] - forward[n])
                    if label >= 0:
                        slope[label] += 1
                    if np.abs(slope).max() < 1e-3:
                        continue
                    slope = slope - decay * field.weights[at]
                    squares[at] += slope * slope
                    field.weights[at] += rate * slope / np.sqrt(squares[at])
        return field


def variants(kind: str, s: str, rng: np.random.Generator) -> str:
    """The same datum as people write it where the fixed patterns don't reach."""
    digits = _digits(s)
    pick = int(rng.integers(3))
    if kind == "email":
        name, _, host = s.partition("@")
        return (f"{name} (at) {host}", f"{name}[at]{host}", f"{name} [at] {host}")[pick]
    if kind == "phone":
        d = digits[-10:].rjust(10, "5")
        return (f"({d[:3]}) {d[3:6]}-{d[6:]}", f"{d[:3]}-{d[3:6]}-{d[6:]}", f"{d[:3]}.{d[3:6]}.{d[6:]}")[pick]
    if kind == "card":
        return ".".join(digits[i : i + 4] for i in range(0, len(digits), 4))
    return s


def labelled(snippets: list[str], seed: int = 3) -> list[tuple[str, list[Span]]]:
    """Training rows: snippets with their base spans, and the same with one span rewritten by ``variants``."""
    rng = np.random.default_rng(seed)
    out = []
    for text in snippets:
        base = base_spans(text)
        base = [s for s in base if not any(o is not s and o[1] <= s[1] and s[2] <= o[2] and (o[2] - o[1], o[0]) > (s[2] - s[1], s[0]) for o in base)]
        out.append((text, base))
        for kind, a, b in base:
            new = variants(kind, text[a:b], rng)
            moved = [(k, x, y) if y <= a else (k, x + len(new) - (b - a), y + len(new) - (b - a)) for k, x, y in base if y <= a or x >= b]
            out.append((text[:a] + new + text[b:], [*moved, (kind, a, a + len(new))]))
    # Plain numbers, dates, versions and amounts are no personal data.
    for _ in range(150):
        n = "".join(map(str, rng.integers(0, 10, int(rng.integers(1, 21)))))
        x, y, z = (int(v) for v in rng.integers(1, 30, 3))
        for number in (n, f"{x}.{y}.{z}", f"{2000 + x}-{y:02d}-{z:02d}", f"{x}.{y}", f"{x} {y} {z}", f"{x}, {y}", f"({x})", f"{x}-{y}", f"{1900 + x} - {1990 + y}"):
            if not base_spans(number):
                out.append((f"the {number} of it.", []))
    return out


def train(df: DataFrame, rows: int = 3000, snippets: int = 400, id_col: str = "doc_id", text_col: str = "text") -> SemiMarkovField:
    """Fit on up to ``snippets`` short passages around digits and at-signs from up to ``rows`` rows of ``df``."""
    ship(df.sparkSession)
    taken = sample(df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")), "id", rows, "pii").select("text").where("text is not null")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = []
            for text in batch.column(0).to_pylist():
                for _, a, b in base_spans(text):
                    found.append(text[max(0, a - 40) : b + 40])
                if (m := TRIGGER.search(text)) is not None:
                    found.append(text[max(0, m.start() - 40) : m.end() + 40])
            yield pa.RecordBatch.from_arrays([pa.array(found, pa.string())], ["snippet"])

    cuts = taken.mapInArrow(cut, "snippet string").distinct()
    found = cuts.orderBy(hash_share(F.col("snippet"), "snippet"), "snippet").limit(snippets).collect()
    return SemiMarkovField.fit(labelled([r["snippet"] for r in found]))


def find(df: DataFrame, model: SemiMarkovField, id_col: str = "doc_id", text_col: str = "text", masked: bool = False) -> DataFrame:
    """``id_col``, ``n_email``, ``n_ip``, ``n_card``, ``n_phone`` (base spans), ``base_sha256``, ``spans`` of every whole text.

    ``masked`` adds ``masked_text``, in which every span is replaced by its kind in angle brackets. A
    null text is an empty one (its masked text stays null). Spans are code points, end exclusive; a
    span of the field is kept where it touches no base span. Texts are read whole, in time linear in
    their length. Repeated rows get equal answers, a null id is carried, an empty table gives an empty
    result; other columns aren't read, whatever their names.
    """
    spark = df.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(model)
    id_type = df.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        field = shared.value
        for batch in batches:
            counts: dict[str, list[int]] = {k: [] for k in KINDS}
            digests, spans, texts = [], [], []
            for value in batch.column(1):
                raw = value.as_py()
                text = raw or ""
                base = base_spans(text)
                every = every_span(text, field, base)
                for k in KINDS:
                    counts[k].append(sum(s[0] == k for s in base))
                digests.append(hashlib.sha256(listed(base).encode()).hexdigest())
                spans.append(listed(every))
                if masked:
                    texts.append(raw if not every else mask(text, every))
            arrays = [batch.column(0), *(pa.array(counts[k], pa.int64()) for k in KINDS), pa.array(digests, pa.string()), pa.array(spans, pa.string())]
            yield pa.RecordBatch.from_arrays([*arrays, *[pa.array(texts, pa.string())] * masked], ["id", *(f"n_{k}" for k in KINDS), "base_sha256", "spans", *["masked_text"] * masked])

    rows = df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    kind = f"id {id_type}, n_email bigint, n_ip bigint, n_card bigint, n_phone bigint, base_sha256 string, spans string" + ", masked_text string" * masked
    return rows.mapInArrow(run, kind).withColumnRenamed("id", id_col)


def every_span(text: str, field: SemiMarkovField, base: list[Span]) -> list[Span]:
    """The base spans and those of the field that touch none of them, by kind, then start."""
    if not TRIGGER.search(text):
        return base
    held = sorted((a, b) for _, a, b in base)
    starts, furthest = [a for a, _ in held], list(accumulate((b for _, b in held), max))
    added = [s for s in field.decode(text) if not (before := bisect_left(starts, s[2])) or furthest[before - 1] <= s[1]]
    return sorted([*base, *added], key=lambda s: (KINDS.index(s[0]), s[1]))


def masked_column(df: DataFrame, model: SemiMarkovField, text_col: str = "text") -> DataFrame:
    """``df`` with the personal data in its texts masked; null texts stay null."""
    ship(df.sparkSession)
    shared = df.sparkSession.sparkContext.broadcast(model)

    @F.arrow_udf("string")
    def masked(texts: pa.Array) -> pa.Array:
        field = shared.value
        out = []
        for value in texts:
            text = value.as_py()
            spans = every_span(text, field, base_spans(text)) if text else []
            out.append(mask(text, spans) if spans else text)
        return pa.array(out, pa.string())

    return df.withColumn(text_col, masked(F.col(text_col).cast("string")))


def mask(text: str, spans: list[Span]) -> str:
    """The text with every span replaced by its kind; of overlapping spans the one that starts first gives the kind."""
    out, done = [], 0
    for kind, a, b in sorted(spans, key=lambda s: (s[1], -s[2])):
        if a >= done:
            out += [text[done:a], f"<{kind}>"]
        done = max(done, b)
    return "".join([*out, text[done:]])
