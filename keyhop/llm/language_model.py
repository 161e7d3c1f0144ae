"""Language-model scoring with a hierarchy of Pitman-Yor processes.

A text is a sequence of words and one end. A word is served in the restaurant of the word before it (of
the end, at the start of a text). The parent of all these is one restaurant without context, whose
parent spells the words: a hierarchy over characters, in which the restaurant of a context of three
characters has as its parent that of the last two, and so on down to a uniform base. The tables of a
word in one restaurant are its customers in the parent, so a word that follows many others is likely
after an unknown one, and spelling is learned from kinds of words rather than from the commonest ones.

The outcomes are those of the add-one base: the words seen in training, and one for all others. So a
word never seen has the probability of a new table with any spelling that is not in the vocabulary.

Seating follows the Chinese restaurant process and is sampled by Gibbs sweeps: all customers of one
dish in one restaurant are taken out and seated anew, given the parents' predictive probabilities and
the other dishes' tables; new tables send customers to the parent. Words are seated by the executors,
next to the counts of word pairs and the vocabulary; the spelling hierarchy has at most ``SYMBOLS`` ** 4
counts whatever the corpus, and is sampled on the driver. Predictive probabilities are averaged over
samples. Random draws come from hashes of the words, the sweep and the sample, so scores repeat however
the rows are dealt to tasks.

The vocabulary and the pair counts are those of all training texts; in pairs a word is its 64-bit hash.
For scoring, the most frequent pairs (a fixed number) are broadcast with their scores; the rest meets
the pair table in a join.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from keyhop.llm.near_duplicates import folded_words  # noqa: F401
from keyhop.llm.sampling import crc_mod
from keyhop.llm.words import pack, parts, unpack, xxhash64
from keyhop.runtime import Scratch, ship

#: Symbols of the spelling model: 0 the start, 1 the end of a word, 2 any other character.
SYMBOLS = 48
ORDER = 3
OTHER = 2
CODE_POINTS = 0x110000
#: The end of a text, as a word; words are never empty.
END = ""
_END_HASH = xxhash64(np.zeros(8, np.uint8), np.zeros(1, np.int64), np.zeros(1, np.int64))[0]


class Speller:
    """Predictive probabilities of the next character after three, for every context and symbol."""

    def __init__(self, symbols: dict[int, int], log_prob: np.ndarray):
        self.symbols, self.log_prob = symbols, log_prob

    @staticmethod
    def keys(words: list[str], symbols: dict[int, int]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Keys (context, symbol) of all words' characters and ends, the words' first positions, and which are other characters."""
        code = np.frombuffer(("\n".join(words) + "\n").encode("utf-32-le", "surrogatepass"), np.uint32)
        lookup = np.full(CODE_POINTS, OTHER, np.int64)
        lookup[list(symbols)] = list(symbols.values())
        lookup[10] = 1
        s = lookup[code]
        ends = np.flatnonzero(s == 1)
        starts = np.concatenate(([0], ends[:-1] + 1))
        previous = np.zeros((ORDER, len(s)), np.int64)
        for k in range(ORDER):
            before = s if k == 0 else previous[k - 1]
            previous[k, 1:] = before[:-1]
            previous[k, starts] = 0
            if k == 0:
                previous[k][previous[k] == 1] = 0
        key = s.copy()
        for k in range(ORDER):
            key += previous[k] * SYMBOLS ** (k + 1)
        return key, starts, s == OTHER

    def log_words(self, words: list[str]) -> np.ndarray:
        """Natural logarithm of each word's probability."""
        if not words:
            return np.zeros(0)
        key, starts, other = self.keys(words, self.symbols)
        return np.add.reduceat(self.log_prob[key] - other * np.log(CODE_POINTS), starts)


def uniform(keys: np.ndarray, step: int) -> np.ndarray:
    """Numbers in [0, 1) that depend on key and step alone, so draws repeat however rows are dealt to tasks."""
    with np.errstate(over="ignore"):
        z = keys.view(np.uint64) + np.uint64(step) * np.uint64(0x9E3779B97F4A7C15)
        z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return ((z ^ (z >> np.uint64(31))) >> np.uint64(11)) * 2.0**-53


#: Above this mean a binomial draw is a rounded normal one; below, the distribution is inverted.
INVERTED = 30.0


def binomial(n: np.ndarray, p: np.ndarray, keys: np.ndarray, step: int) -> np.ndarray:
    """A draw for each row from its key and the step (steps that are used together differ by two)."""
    u = uniform(keys, step)
    out = (u < p).astype(np.int64)
    large = np.flatnonzero((n > 1) & (n * p >= INVERTED))
    if len(large):
        normal = np.sqrt(-2 * np.log1p(-u[large])) * np.cos(2 * np.pi * uniform(keys[large], step + 1))
        mean = n[large] * p[large]
        out[large] = np.clip(np.rint(mean + np.sqrt(mean * (1 - p[large])) * normal), 0, n[large]).astype(np.int64)
    at = np.flatnonzero((n > 1) & (n * p < INVERTED))
    m, odds, rest = n[at], p[at] / np.maximum(1 - p[at], 1e-300), u[at]
    chance, k = (1 - p[at]) ** m, 0
    while len(at):
        out[at] = k
        rest = rest - chance
        on = (rest >= 0) & (k < m)
        at, m, odds, rest, chance = at[on], m[on], odds[on], rest[on], chance[on]
        chance = chance * (m - k) / (k + 1) * odds
        k += 1
    return out


def seat(customers: np.ndarray, mass: np.ndarray, discount: float, keys: np.ndarray, seed: int = 0) -> np.ndarray:
    """Numbers of tables after seating each dish's customers anew.

    ``mass`` is what a new table weighs: (strength + discount * tables of the restaurant) times the
    parent's probability of the dish. Customers enter one by one at first, then in blocks of a tenth of
    those seated, within which the chance of a new table is taken as constant. ``keys`` tell the dishes
    apart in the draws: a dish's tables depend on its key, its customers, its mass and ``seed``, and not
    on what stands beside it.
    """
    tables = np.minimum(customers, 1).astype(np.int64)
    at = np.flatnonzero(customers > 1)
    seated, c, weight = np.ones(len(at), np.int64), customers[at].astype(np.int64), np.maximum(mass[at], 0)
    t, own, step = np.ones(len(at), np.int64), keys[at], seed << 20
    while len(at):
        block = np.minimum(np.maximum(seated // 10, 1), c - seated)
        t = t + binomial(block, weight / (weight + seated - discount * t), own, step)
        seated, step = seated + block, step + 2
        tables[at] = t
        on = seated < c
        if not on.all():
            at, seated, c, weight, t, own = at[on], seated[on], c[on], weight[on], t[on], own[on]
    return tables


def discount_of(once: float, twice: float) -> float:
    """The usual estimate from how many dishes were ordered once and twice."""
    return float(min(max(once / (once + 2 * twice), 0.05), 0.95)) if once else 0.5


def sample_speller(counts: np.ndarray, burn: int = 8, keep: int = 6, strength: float = 1.0, seed: int = 1) -> np.ndarray:
    """Averaged log predictive probabilities of the hierarchy, from the counts of (context, symbol)."""
    shapes = [SYMBOLS ** (k + 1) for k in range(ORDER + 1)]  # level k: contexts of k characters
    uniform = 1 / SYMBOLS
    predictive = [np.full(n, uniform) for n in shapes]
    total, counts = np.zeros(shapes[ORDER]), counts.astype(np.float64)
    tables: list[np.ndarray] = [np.zeros(0)] * (ORDER + 1)
    for sweep in range(burn + keep):
        customers = [np.zeros(0)] * (ORDER + 1)
        customers[ORDER] = counts
        discounts = [0.5] * (ORDER + 1)
        for k in range(ORDER, -1, -1):
            c = customers[k]
            discounts[k] = discount_of((c == 1).sum(), (c == 2).sum())
            parent = predictive[k - 1] if k else np.full(SYMBOLS, uniform)
            at = np.flatnonzero(c)
            base = parent[at % shapes[k - 1]] if k else parent[at]
            of_context = (tables[k] if len(tables[k]) else np.minimum(c, 1)).reshape(-1, SYMBOLS).sum(axis=1)
            tables[k] = np.zeros(0)
            got = np.zeros(len(c))
            got[at] = seat(c[at], (strength + discounts[k] * of_context[at // SYMBOLS]) * base, discounts[k], at, (seed * (burn + keep) + sweep) * (ORDER + 1) + k)
            tables[k] = got
            if k:
                customers[k - 1] = got.reshape(SYMBOLS, -1).sum(axis=0)  # the oldest character is forgotten
        for k in range(ORDER + 1):
            c, t = customers[k].reshape(-1, SYMBOLS), tables[k].reshape(-1, SYMBOLS)
            d = discounts[k]
            predictive[k] = np.zeros(0)  # in place from here on: these arrays are the driver's largest
            p = d * t
            np.subtract(c, p, out=p)
            np.maximum(p, 0, out=p)
            weight = strength + d * t.sum(axis=1, keepdims=True)
            if k:
                parent, by_oldest = predictive[k - 1].reshape(-1, SYMBOLS), p.reshape(SYMBOLS, -1, SYMBOLS)
                for i, of_contexts in enumerate(weight.reshape(SYMBOLS, -1, 1)):
                    by_oldest[i] += of_contexts * parent
            else:
                p += weight * uniform
            p /= strength + c.sum(axis=1, keepdims=True)
            predictive[k] = p.ravel()
        if sweep >= burn:
            total += predictive[ORDER]
    total /= keep
    return np.log(total, out=total).astype(np.float32)


def vocabulary(docs: DataFrame) -> DataFrame:
    """``word`` and ``c``, its count in rows where ``own`` holds, for every word of ``text``."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            own = batch.column(0).to_numpy(zero_copy_only=False)
            for at, to, words in parts(batch.column(1)):
                h, first, place = np.unique(words.hash, return_index=True, return_inverse=True)
                c = np.bincount(place, weights=own[at:to][words.of], minlength=len(h)).astype(np.int64)
                yield pa.RecordBatch.from_arrays([words.strings(first), pa.array(c)], ["word", "c"])

    return docs.select("own", "text").mapInArrow(count, "word string, c bigint").groupBy("word").agg(F.sum("c").alias("c"))


def _symbols(vocab: DataFrame) -> dict[int, int]:
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            code, n = np.unique(np.frombuffer("".join(batch.column(0).to_pylist()).encode("utf-32-le", "surrogatepass"), np.uint32), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(code.astype(np.int32)), pa.array(n, pa.int64())], ["code", "n"])

    found = vocab.select("word").mapInArrow(count, "code int, n bigint").groupBy("code").agg(F.sum("n").alias("n"))
    top = found.orderBy(F.desc("n"), "code").limit(SYMBOLS - OTHER - 1).collect()
    return {r["code"]: OTHER + 1 + i for i, r in enumerate(top)}


def _spelling_counts(vocab: DataFrame, symbols: dict[int, int], tables: Column) -> np.ndarray:
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: np.ndarray | None = None
        for batch in batches:
            words = batch.column(0).to_pylist()
            if not words:
                continue
            key, starts, _ = Speller.keys(words, symbols)
            weight = np.repeat(batch.column(1).to_numpy(), np.diff(np.append(starts, len(key))))
            held, place = np.unique(key, return_inverse=True)
            total = np.zeros(SYMBOLS ** (ORDER + 1)) if total is None else total
            total[held] += np.bincount(place, weights=weight)
        at = np.flatnonzero(total) if total is not None else np.zeros(0, np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(total[at].astype(np.int64) if len(at) else at, pa.int64())], ["key", "n"])

    rows = vocab.select("word", tables.cast("bigint").alias("t")).mapInArrow(count, "key bigint, n bigint").groupBy("key").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(SYMBOLS ** (ORDER + 1), np.int64)
    out[rows.column("key").to_numpy()] = rows.column("n").to_numpy()
    return out


def _joined(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of ``rows`` or more, but for the last."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        held.append(batch)
        if sum(x.num_rows for x in held) >= rows:
            yield pa.concat_batches(held)
            held = []
    if held:
        yield pa.concat_batches(held)


def _seated(guests: DataFrame, speller: Speller, discount: float, tables: float, samples: int, strength: float, seed: int) -> DataFrame:
    """``guests`` with ``spelled`` (natural log) and ``t``, the tables of ``k`` customers in each of ``samples`` seatings."""
    shared = guests.sparkSession.sparkContext.broadcast(speller)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _joined(batches, 200_000):
            spelled = shared.value.log_words(batch.column(0).to_pylist())
            k, h = batch.column(3).to_numpy(), batch.column(2).to_numpy()
            mass = (strength + discount * tables) * np.exp(spelled)
            t = np.array([seat(k, mass, discount, h, seed * samples + i) for i in range(samples)]).reshape(samples, -1).T
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(k) + 1) * samples, pa.int32()), pa.array(t.ravel(), pa.int64()))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(spelled, pa.float64()), lists], names)

    kind = "word string, c bigint, h bigint, k bigint, tu double, p0 double, tu0 double, spelled double, t array<bigint>"
    names = [x.split()[0] for x in kind.split(", ")]
    return guests.select(names[:7]).mapInArrow(run, kind)


def hashed(words: Column) -> Column:
    """The hashes of a text's words between two ends; neighbours are the pairs."""
    end = F.array(F.xxhash64(F.lit(END)))
    return F.concat(end, F.transform(words, lambda w: F.xxhash64(w)), end)


def mixed(u: np.ndarray, w: np.ndarray) -> np.ndarray:
    """One number for a pair of codes; equal pairs have equal ones."""
    return u.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15) ^ w.view(np.uint64)


class Frequent:
    """The frequent words, by rank. A word's code is its rank, or its hash if it is a rare one.

    Words whose hash is as small as a rank count as frequent ones, so that no code means two words.
    """

    #: Ranks are smaller than this, and hashes of rare words are not.
    LIMIT = 1 << 26

    def __init__(self, h: np.ndarray, c: np.ndarray):
        by = np.lexsort((h, -c))
        self.h, self.c = h[by], c[by]
        self.rank = np.argsort(self.h).astype(np.int32)
        self.sorted = self.h[self.rank]

    def find(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ranks of hashes, and which have one."""
        if not len(self.h):
            return np.zeros(len(h), np.int64), np.zeros(len(h), bool)
        at = np.minimum(np.searchsorted(self.sorted, h), len(self.h) - 1)
        return self.rank[at].astype(np.int64), self.sorted[at] == h

    def codes(self, h: np.ndarray) -> np.ndarray:
        rank, there = self.find(h)
        return np.where(there, rank, h)

    def hashes(self, codes: np.ndarray) -> np.ndarray:
        out, at = codes.copy(), np.flatnonzero(~rare(codes))
        out[at] = self.h[codes[at]]
        return out

    def __getstate__(self) -> bytes:
        return pack(self.h, self.c)

    def __setstate__(self, state: bytes) -> None:
        self.__init__(*unpack(state, 2))


def rare(codes: np.ndarray) -> np.ndarray:
    return (codes < 0) | (codes >= Frequent.LIMIT)


def _is_rare(code: str) -> Column:
    return (F.col(code) < 0) | (F.col(code) >= Frequent.LIMIT)


def _is_frequent(least: int) -> Column:
    return (F.col("c") >= least) | F.col("h").between(0, Frequent.LIMIT - 1)


def frequent_words(vocab: DataFrame, most: int) -> tuple[Frequent, int]:
    """The words of the greatest counts, at most ``most``, and the least of their counts."""
    by_count = vocab.where("c > 0").groupBy("c").agg(F.count(F.lit(1)).alias("n")).toArrow()
    c, n = by_count.column("c").to_numpy(), by_count.column("n").to_numpy()
    down = np.argsort(-c)
    held = int(np.searchsorted(np.cumsum(n[down]), most, "right"))
    least = int(c[down[held - 1]]) if held else int(c.max(initial=0)) + 1
    top = vocab.where(_is_frequent(least)).select("h", "c").toArrow()
    return Frequent(top.column("h").to_numpy(), top.column("c").to_numpy()), least


_DEALT = "packed binary, entries binary, once bigint, twice bigint, u bigint, w bigint, c bigint, rows array<bigint>, times array<bigint>, row bigint, id {id}, n bigint, known bigint, base double"


def _filled(schema: pa.Schema, size: int, **columns: pa.Array) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([columns.get(f.name, pa.nulls(size, f.type)) for f in schema], schema=schema)


def _base(c: np.ndarray, outcomes: float) -> np.ndarray:
    return np.log10((c + 1) / outcomes)


def deal_pairs(docs: DataFrame, shared, outcomes: float, tasks: int) -> DataFrame:
    """All pairs of neighbours, each with its count in rows where ``own`` holds and the rows that have it.

    The pairs of frequent words are rows of one packed column (former, latter, count, rows that have it;
    then row and times for each of these); pairs with a rare word have columns of their own; and each row
    of ``docs`` has one, with its words' number and what its frequent words give to ``known`` and
    ``base``. Pairs are dealt to ``tasks`` by a hash of both words: no context lies in one task.
    """
    id_type = docs.schema["id"].dataType.simpleString()

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = shared.value
        base = _base(held.c, outcomes)
        row = TaskContext.get().partitionId() << 33
        for batch in batches:
            schema = pa.schema([("task", pa.int32()), ("packed", pa.binary()), ("row", pa.int64()), ("id", batch.column(0).type), ("n", pa.int64()), ("known", pa.int64()), ("base", pa.float64())])
            own = batch.column(1).to_numpy(zero_copy_only=False)
            for at, to, words in parts(batch.column(2)):
                found, place = np.unique(np.append(words.hash, _END_HASH), return_inverse=True)
                code = held.codes(found)
                by = np.argsort(code)
                code, local = code[by], np.argsort(by)[place]
                lengths = words.count + 1
                ends = np.cumsum(lengths) - 1
                w = np.full(int(lengths.sum()), local[-1])
                inner = np.ones(len(w), bool)
                inner[ends] = False
                w[inner] = local[:-1]
                u = np.append(local[-1], w[:-1])
                of = np.repeat(np.arange(to - at), lengths)
                rank = np.where(rare(code), -1, code)[w]
                top = rank >= 0
                known = np.bincount(of[top], weights=held.c[rank[top]] > 0, minlength=to - at).astype(np.int64)
                sums = np.bincount(of[top], weights=base[rank[top]], minlength=to - at)
                rows = row + np.arange(to - at)
                yield _filled(schema, to - at, task=pa.array(rows % tasks, pa.int32()), row=pa.array(rows), id=batch.column(0).slice(at, to - at), n=pa.array(lengths), known=pa.array(known), base=pa.array(sums))
                d = len(code)
                task = ((mixed(code[u], code[w]) * np.uint64(0xD6E8FEB86659FD93)) >> np.uint64(40)) % np.uint64(tasks)
                key = (task.astype(np.int64) * d + u) * d + w
                order = np.argsort(key, kind="stable")
                key, of, mine = key[order], of[order], own[at:to][of[order]]
                new = np.append(True, key[1:] != key[:-1])
                pair = np.flatnonzero(new)
                entry = np.flatnonzero(new | np.append(True, of[1:] != of[:-1]))
                c = np.add.reduceat(mine.astype(np.int64), pair)
                times = np.diff(np.append(entry, len(key)))
                first = np.searchsorted(entry, np.append(pair, len(key)))  # of each pair's entries
                key = key[pair]
                task, u, w = key // (d * d), code[key // d % d], code[key % d]
                cut = np.flatnonzero(np.append(True, task[1:] != task[:-1]))
                blobs = [pack(u[a:b], w[a:b], c[a:b], np.diff(first[a : b + 1]), rows[of[entry[first[a] : first[b]]]], times[first[a] : first[b]]) for a, b in zip(cut, np.append(cut[1:], len(task)), strict=True)]
                yield _filled(schema, len(cut), task=pa.array(task[cut], pa.int32()), packed=pa.array(blobs, pa.binary()))
                row += to - at

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema, blobs = None, []
        for batch in batches:
            schema = schema or pa.schema([("packed", pa.binary()), ("entries", pa.binary()), *((x, pa.int64()) for x in ("once", "twice", "u", "w", "c")), ("rows", pa.list_(pa.int64())), ("times", pa.list_(pa.int64())), *(batch.schema.field(i) for i in range(2, 7))])
            blobs += batch.column(1).drop_null().to_pylist()
            docs = batch.filter(pc.is_valid(batch.column(2)))
            if docs.num_rows:
                yield _filled(schema, docs.num_rows, **{x: docs.column(x) for x in ("row", "id", "n", "known", "base")})
        if not blobs:
            return
        u, w, c, n, rows, times = (np.concatenate(x) for x in zip(*(unpack(b, 6) for b in blobs), strict=True))
        blobs.clear()
        order = np.lexsort((w, u))
        start, u, w, c, n = (np.cumsum(n) - n)[order], u[order], w[order], c[order], n[order]
        ends = np.cumsum(n)
        place = np.arange(len(rows)) + np.repeat(start - (ends - n), n)
        rows, times = rows[place], times[place]
        pair = np.flatnonzero(np.append(True, (u[1:] != u[:-1]) | (w[1:] != w[:-1])))
        u, w, c, n = u[pair], w[pair], np.add.reduceat(c, pair), np.add.reduceat(n, pair)
        once, twice = int((c == 1).sum()), int((c == 2).sum())
        apart = rare(u) | rare(w)
        entry = np.repeat(apart, n)
        packed, entries = pack(u[~apart], w[~apart], c[~apart]), pack(n[~apart], rows[~entry], times[~entry])
        yield _filled(schema, 1, packed=pa.array([packed], pa.binary()), entries=pa.array([entries], pa.binary()), once=pa.array([once]), twice=pa.array([twice]))
        offsets = pa.array(np.append(0, np.cumsum(n[apart])), pa.int32())
        lists = [pa.ListArray.from_arrays(offsets, pa.array(x[entry])) for x in (rows, times)]
        yield _filled(schema, int(apart.sum()), u=pa.array(u[apart]), w=pa.array(w[apart]), c=pa.array(c[apart]), rows=lists[0], times=lists[1])

    dealt = docs.select("id", "own", "text").mapInArrow(deal, f"task int, packed binary, row bigint, id {id_type}, n bigint, known bigint, base double")
    return dealt.repartitionById(tasks, "task").mapInArrow(merge, _DEALT.format(id=id_type))


class Tables:
    """What pairs of codes are scored with: of contexts and words their statistics, of pairs their seating.

    ``p`` and ``tu`` are the latter's parent probability and the former's tables, ``p0`` and ``tu0`` those
    that the last seating of pairs was drawn with (none before the first).
    """

    NAMES = ("p", "tu", "p0", "tu0", "cu")

    def __init__(self, stats: dict[str, np.ndarray], discount: float, strength: float, samples: int, seed: int | None):
        self.stats, self.discount, self.strength, self.samples, self.seed = stats, discount, strength, samples, seed

    def of(self, u: np.ndarray, w: np.ndarray, given: dict[str, np.ndarray] | None = None) -> dict[str, np.ndarray]:
        """The statistics of pairs; those of rare words are ``given``."""
        out = {}
        for name in self.NAMES:
            code = w if name in ("p", "p0") else u
            if given is None:
                out[name] = self.stats[name][code]
            else:
                out[name] = given[name].copy()
                at = np.flatnonzero(~rare(code))
                out[name][at] = self.stats[name][code[at]]
        return out

    def seat(self, held: Frequent, u: np.ndarray, w: np.ndarray, c: np.ndarray, of: dict[str, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        """Mean tables of all seatings, and those of the first; drawn by the words' hashes, whatever words are frequent."""
        first = np.minimum(c, 1)
        t = first.astype(np.float64)
        at = np.flatnonzero(c > 1) if self.seed is not None else []
        if len(at):
            mass = (self.strength + self.discount * of["tu0"][at]) * of["p0"][at]
            keys = mixed(held.hashes(u[at]), held.hashes(w[at]))
            drawn = [seat(c[at], mass, self.discount, keys, self.seed * self.samples + i) for i in range(self.samples)]
            t[at], first[at] = np.mean(drawn, axis=0), drawn[0]
        return t, first

    def score(self, held: Frequent, u: np.ndarray, w: np.ndarray, c: np.ndarray, of: dict[str, np.ndarray]) -> np.ndarray:
        t, d, s = self.seat(held, u, w, c, of)[0], self.discount, self.strength
        return np.log10((np.maximum(c - d * t, 0) + (s + d * of["tu"]) * of["p"]) / (s + of["cu"]))


_WORDS = "p double, tu double, p0 double, tu0 double, cu bigint, cw bigint"


def _with_words(pairs: DataFrame, words: DataFrame) -> DataFrame:
    """``pairs`` of which a word is rare, with the statistics of the rare ones."""
    of_w = words.select(F.col("h").alias("w"), "p", "p0", F.col("c").alias("cw"))
    of_u = words.select(F.col("h").alias("u"), "tu", "tu0", F.col("c").alias("cu"))
    nothing = lambda x, kind: F.lit(None).cast(kind).alias(x)
    own = pairs.columns
    both = pairs.where(_is_rare("w")).join(of_w, "w").select(*own, "p", "p0", "cw")
    both = both.union(pairs.where(~_is_rare("w")).select(*own, nothing("p", "double"), nothing("p0", "double"), nothing("cw", "bigint")))
    names = [*own, "p", "tu", "p0", "tu0", "cu", "cw"]
    return both.where(_is_rare("u")).join(of_u, "u").select(names).union(both.where(~_is_rare("u")).withColumns({"tu": F.lit(None).cast("double"), "tu0": F.lit(None).cast("double"), "cu": F.lit(None).cast("bigint")}).select(names))


def _given(batch: pa.RecordBatch) -> dict[str, np.ndarray]:
    column = lambda x: batch.column(x).to_numpy(zero_copy_only=False).astype(np.float64)
    return {x: column(x) for x in Tables.NAMES}


class Model:
    """The pairs as dealt, what they are scored with, and totals."""

    def __init__(self, dealt: DataFrame, held: Frequent, shared, outcomes: float, samples: int, totals: dict):
        self.dealt, self.held, self.shared, self.outcomes, self.samples, self.totals = dealt, held, shared, outcomes, samples, totals
        self.tables, self.words, self.sent = None, None, None

    @property
    def packed(self) -> DataFrame:
        return self.dealt.where("packed is not null").select("packed", "entries")

    @property
    def apart(self) -> DataFrame:
        return self.dealt.where("u is not null").select("u", "w", "c", "rows", "times")

    def take(self, words: DataFrame, least: int, seed: int | None, **options) -> None:
        """Seat by draws of ``seed`` and score by ``words`` (``h``, ``c``, statistics) from now on; the frequent ones are sent out."""
        held, stats = self.held, {}
        for names in (("p", "tu"), ("p0", "tu0")):  # half of them at a time, for the driver's memory
            top = words.where(_is_frequent(least)).select("h", *names).toArrow()
            rank, _ = held.find(top.column("h").to_numpy())
            for name in names:
                stats[name] = np.zeros(len(held.h))
                stats[name][rank] = top.column(name).to_numpy(zero_copy_only=False)
            del top, rank
        stats["cu"] = held.c
        if self.sent is not None:
            self.sent.unpersist()
        self.sent = words.sparkSession.sparkContext.broadcast(Tables(stats, seed=seed, **options))
        del stats
        self.words = words.where(~_is_frequent(least))

    def sums(self) -> DataFrame:
        """Of every word ``h``: ``k``, its customers from pairs (the first seating), and ``tu``, the mean tables of its context."""
        shared, sent, samples, size = self.shared, self.sent, self.samples, 100_000
        blocks = len(self.held.h) // size + 1

        def of_packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held = shared.value
            for batch in batches:
                for blob in batch.column(0).to_pylist():
                    u, w, c = unpack(blob, 3)
                    u, w, c = u[c > 0], w[c > 0], c[c > 0]
                    first, t = np.minimum(c, 1), np.minimum(c, 1)
                    if sent is not None:
                        t, first = sent.value.seat(held, u, w, c, sent.value.of(u, w))
                    k, tu = np.bincount(w, weights=first, minlength=len(held.h)), np.bincount(u, weights=t, minlength=len(held.h))
                    for block in range(0, len(k), size):
                        at = block + np.flatnonzero((k + tu)[block : block + size])
                        packed = pack(at, k[at].astype(np.int64), np.rint(tu[at] * samples).astype(np.int64))
                        yield pa.RecordBatch.from_arrays([pa.array([block // size], pa.int32()), pa.array([packed], pa.binary())], ["block", "packed"])

        def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held, k, tu = shared.value, None, None
            for batch in batches:
                for blob in batch.column(1).to_pylist():
                    if k is None:
                        k, tu = np.zeros(len(held.h), np.int64), np.zeros(len(held.h), np.int64)
                    at, more, tables = unpack(blob, 3)
                    k[at] += more
                    tu[at] += tables
            if k is not None:
                at = np.flatnonzero(k + tu)
                yield pa.RecordBatch.from_arrays([pa.array(held.h[at]), pa.array(k[at]), pa.array(tu[at] / samples)], ["h", "k", "tu"])

        def of_apart(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held = shared.value
            for batch in batches:
                u, w, c = (batch.column(i).to_numpy() for i in range(3))
                t, first = sent.value.seat(held, u, w, c, sent.value.of(u, w, _given(batch))) if sent is not None else (np.minimum(c, 1), np.minimum(c, 1))
                h = np.append(held.hashes(w), held.hashes(u))
                k, tu = np.append(first, np.zeros(len(u), np.int64)), np.append(np.zeros(len(u)), t)
                yield pa.RecordBatch.from_arrays([pa.array(h), pa.array(k), pa.array(tu, pa.float64())], ["h", "k", "tu"])

        kind = "h bigint, k bigint, tu double"
        rows = self.apart.select("u", "w", "c")
        again = rows.where("c > 1")
        packed = self.packed.select("packed").mapInArrow(of_packed, "block int, packed binary")
        parts = [packed.repartitionById(blocks, "block").mapInArrow(add, kind)]
        if sent is None:
            parts.append(rows.where("c > 0").mapInArrow(of_apart, kind))
        else:
            parts += [_with_words(again, self.words).mapInArrow(of_apart, kind)]
            for code, k, tu in (("w", 1, 0.0), ("u", 0, 1.0)):  # one customer, one table
                single = rows.where("c = 1")
                parts.append(single.where(_is_rare(code)).select(F.col(code).alias("h"), F.lit(k).cast("bigint").alias("k"), F.lit(tu).alias("tu")))
                parts.append(single.where(~_is_rare(code)).select(code).mapInArrow(self._once(k, tu), kind))
        every = parts[0]
        for part in parts[1:]:
            every = every.union(part)
        return every.groupBy("h").agg(F.sum("k").alias("k"), F.sum("tu").alias("tu"))

    def _once(self, k: int, tu: float):
        shared = self.shared

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                h, n = np.unique(shared.value.hashes(batch.column(0).to_numpy()), return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(h), pa.array(n * k), pa.array(n * tu)], ["h", "k", "tu"])

        return run

    def scored(self, packed, apart, kind: str) -> DataFrame:
        """``packed`` and ``apart`` make rows of ``kind`` of (u, w, c, known, base, score, entries, rows, times), for pairs of frequent words and others."""
        shared, sent, outcomes = self.shared, self.sent, self.outcomes

        def of_packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for blob, entries in zip(batch.column(0), batch.column(1), strict=True):
                    u, w, c = unpack(blob.as_py(), 3)
                    if len(u):
                        n, rows, times = unpack(entries.as_py(), 3)
                        cw = shared.value.c[w]
                        yield packed(u, w, c, cw > 0, _base(cw, outcomes), sent.value.score(shared.value, u, w, c, sent.value.of(u, w)), n, rows, times)

        def of_apart(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                u, w, c = (batch.column(x).to_numpy() for x in ("u", "w", "c"))
                if not len(u):
                    continue
                far = rare(w)
                cw = batch.column("cw").to_numpy(zero_copy_only=False).astype(np.float64)
                cw[~far] = shared.value.c[w[~far]]
                n = np.asarray(pc.list_value_length(batch.column("rows"))).astype(np.int64)
                rows, times = (batch.column(x).flatten().to_numpy() for x in ("rows", "times"))
                yield apart(u, w, c, cw > 0, _base(cw, outcomes), sent.value.score(shared.value, u, w, c, sent.value.of(u, w, _given(batch))), n, rows, times)

        return self.packed.mapInArrow(of_packed, kind).union(_with_words(self.apart, self.words).mapInArrow(of_apart, kind))


def learn(docs: DataFrame, scratch: Scratch, samples: int = 4, sweeps: int = 2, strength: float = 1.0, frequent: int = 800_000, pairs: int = 1_200_000) -> Model:
    """The model of ``docs`` (``id``, ``own`` for the rows to learn from, ``text``), and all their pairs dealt.

    A task gets about ``pairs`` words and their former ones.
    """
    spark = docs.sparkSession
    ends = spark.createDataFrame([(END, docs.where("own").count())], "word string, c bigint")
    vocab = scratch.save(vocabulary(docs).union(ends).withColumn("h", F.xxhash64("word")), "vocabulary")
    stat = vocab.agg(F.sum("c").alias("n"), F.count_if(F.col("c") > 0).alias("v")).first()
    n, v = stat["n"] or 0, stat["v"] or 0
    held, least = frequent_words(vocab, frequent)
    shared, outcomes = spark.sparkContext.broadcast(held), float(n + v + 1)
    scratch.release()
    symbols = _symbols(vocab)
    dealt = scratch.save(deal_pairs(docs, shared, outcomes, n // pairs + 1), "pairs")
    scratch.release()
    stat = dealt.agg(F.sum("once").alias("once"), F.sum("twice").alias("twice")).first()
    of_pairs = discount_of(stat["once"] or 0, stat["twice"] or 0)
    model = Model(dealt, held, shared, outcomes, samples, {"n": n, "v": v, "discount": of_pairs})
    tables: Column = F.least(F.col("k"), F.lit(1))
    seated, total = None, [float(v)] * samples
    nothing = F.lit(None).cast("double")
    for sweep in range(sweeps):
        own = vocab.select("word", "c", "h", nothing.alias("p0"), nothing.alias("tu0")) if seated is None else seated.select("word", "c", "h", F.col("p").alias("p0"), F.col("tu").alias("tu0"), "t")
        guests = own.join(model.sums(), "h", "left").withColumns({"k": F.coalesce("k", F.lit(0).cast("bigint")), "tu": F.coalesce("tu", F.lit(0.0))})
        guests = scratch.save(guests, f"customers{sweep}")
        scratch.release()
        stat = guests.agg(F.sum("k").alias("k"), F.count_if(F.col("k") == 1).alias("once"), F.count_if(F.col("k") == 2).alias("twice")).first()
        guest, discount = stat["k"] or 0, discount_of(stat["once"], stat["twice"])
        speller = Speller(symbols, sample_speller(_spelling_counts(guests, symbols, tables), seed=sweep + 1))
        drawn = scratch.save(_seated(guests, speller, discount, total[0], samples, strength, sweep), f"drawn{sweep}")
        sums = drawn.agg(*(F.sum(F.get("t", F.lit(i))).alias(f"t{i}") for i in range(samples))).first()
        total = [float(x or 0) for x in sums]
        tables = F.get("t", F.lit(0))
        c, k = F.col("c"), F.col("k")
        known = drawn.where(c > 0).agg(F.sum(F.exp("spelled"))).first()[0] or 0.0
        parent = F.when(c > 0, F.exp("spelled")).otherwise(F.lit(max(1.0 - known, 1e-9)))
        each = [(F.greatest(k - discount * F.get("t", F.lit(i)), F.lit(0.0)) + (strength + discount * total[i]) * parent) / (strength + guest) for i in range(samples)]
        seated = drawn.withColumn("p", sum(each[1:], each[0]) / samples).select("word", "c", "h", "p", "tu", "p0", "tu0", "t")
        if sweep < sweeps - 1:  # pairs are seated anew by what is known now
            model.take(seated.withColumns({"p0": F.col("p"), "tu0": F.col("tu")}), least, sweep, discount=of_pairs, strength=strength, samples=samples)
        else:  # the seating that the customers came from
            model.take(seated, least, sweep - 1 if sweep else None, discount=of_pairs, strength=strength, samples=samples)
        for name in ("vocabulary" if sweep == 0 else f"drawn{sweep - 1}", f"customers{sweep}"):
            scratch.drop(name)
    return model


def _docs(df: DataFrame, train_rows: Column, id_col: str, text_col: str) -> DataFrame:
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    return df.select(F.col(id_col).alias("id"), F.coalesce(train_rows, F.lit(False)).alias("own"), text.alias("text"))


def train(df: DataFrame, train_rows: Column, scratch: Scratch, id_col: str = "doc_id", text_col: str = "text", **options) -> tuple[DataFrame, dict]:
    """All pairs of words of the texts, by their hashes (``u``, ``w``, ``c``, ``known``, ``base``, ``score``), and totals.

    ``base`` is the add-one unigram's log10 probability of the latter word, ``score`` that of the
    hierarchy after the former; pairs of which ``train_rows`` has none (c = 0) are scored too.
    """
    ship(df.sparkSession)
    model = learn(_docs(df, train_rows, id_col, text_col), scratch, **options)
    shared = model.shared

    def pairs(u, w, c, known, base, score, n, rows, times) -> pa.RecordBatch:
        held = shared.value
        return pa.RecordBatch.from_arrays([pa.array(held.hashes(u)), pa.array(held.hashes(w)), pa.array(c), pa.array(known), pa.array(base), pa.array(score)], ["u", "w", "c", "known", "base", "score"])

    return model.scored(pairs, pairs, "u bigint, w bigint, c bigint, known boolean, base double, score double"), model.totals


def score(df: DataFrame, train_rows: Column, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """Per row: id, ``n_tokens``, ``n_known``, ``train_tokens``, ``base_score`` and ``score``.

    ``train_rows`` tells which rows are learned from. A null text is an empty one: its only token is the
    end. Rows count one by one, whatever their ids; repeated rows get equal scores. Texts are read whole
    at any length. ``frequent`` words at most are broadcast. An empty table gives an empty result; without
    training rows every word is unknown. Other columns are read by ``train_rows`` alone, whatever their
    names.
    """
    spark = df.sparkSession
    ship(spark)
    scratch = Scratch(spark, "language-model")
    model = learn(_docs(df, train_rows, id_col, text_col), scratch, **options)

    def of_rows(rows: np.ndarray, times: np.ndarray, n: np.ndarray, *columns: np.ndarray) -> pa.RecordBatch:
        row, place = np.unique(rows, return_inverse=True)
        sums = [np.bincount(place, weights=times * np.repeat(x, n), minlength=len(row)) for x in columns]
        return pa.RecordBatch.from_arrays([pa.array(row), pa.array(sums[0].astype(np.int64)), pa.array(sums[1]), pa.array(sums[2])], ["row", "known", "base", "score"])

    def packed(u, w, c, known, base, score, n, rows, times) -> pa.RecordBatch:  # known and base are with the rows
        row, place = np.unique(rows, return_inverse=True)
        sums = np.bincount(place, weights=times * np.repeat(score, n), minlength=len(row))
        return pa.RecordBatch.from_arrays([pa.array(row), pa.array(np.zeros(len(row), np.int64)), pa.array(np.zeros(len(row))), pa.array(sums)], ["row", "known", "base", "score"])

    def apart(u, w, c, known, base, score, n, rows, times) -> pa.RecordBatch:
        far = rare(w)
        return of_rows(rows, times, n, far & known, np.where(far, base, 0.0), score)

    given = model.scored(packed, apart, "row bigint, known bigint, base double, score double")
    id_type = model.dealt.schema["id"].dataType.simpleString()
    own = model.dealt.where("row is not null").select("row", "id", "n", "known", "base", F.lit(0.0).alias("score"))
    every = own.union(given.select("row", F.lit(None).cast(id_type), F.lit(None).cast("bigint"), "known", "base", "score"))
    sums = every.groupBy("row").agg(F.max("id").alias("id"), F.max("n").alias("n"), *(F.sum(x).alias(x) for x in ("known", "base", "score")))
    return sums.select(F.col("id").alias(id_col), F.col("n").alias("n_tokens"), F.col("known").alias("n_known"), F.lit(model.totals["n"]).cast("bigint").alias("train_tokens"), F.col("base").alias("base_score"), "score")


def perplexity(scored: DataFrame, by: str, score_col: str = "score") -> DataFrame:
    """Per value of ``by``: tokens and perplexity for each token."""
    return scored.groupBy(by).agg(F.sum("n_tokens").alias("tokens"), F.pow(F.lit(10.0), -F.sum(score_col) / F.sum("n_tokens")).alias("perplexity"))


def held_out(id_col: str = "doc_id") -> Column:
    """The rows that training must not see."""
    return F.coalesce(crc_mod(F.col(id_col), 7) == 2, F.lit(False))
