"""The strategies over one store, their counters, and what they cost.

crawl scans the bounding interval; leap jumps at every mismatch; hybrid jumps where the mismatch is
above a threshold and scans where it isn't. All take the same rows. Two executors. The declarative one
gets the counters by aggregation: mismatching rows with the same next match form one gap; leap jumps
once for each gap, and hybrid scans a gap's rows up to the first whose mismatch is above the threshold.
The cursor walks each slice's sorted rows as the strategy says, in Arrow batches, with a binary search
for each jump. Mismatches and next matches are column expressions in both.
"""

from __future__ import annotations

from bisect import bisect_left
from collections import Counter
from collections.abc import Iterator
from decimal import Decimal

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from keyhop.functions.bits import LIMB, ones, tail
from keyhop.plans import columns, costs
from keyhop.plans.costs import Counters
from keyhop.plans.search import Search
from keyhop.runtime import ship
from keyhop.sources.store import KeyedStore


def walk(keys: list[int], search: Search, threshold: int, threshold_above: int | None = None, cluster_end: bool = False) -> tuple[list[int], Counters]:
    """Walk sorted keys; returns the positions taken and the counters.

    ``threshold`` 0 is leap, n is crawl. ``threshold_above`` is a lower threshold for keys above their
    pattern. ``cluster_end``: after a match, take what follows up to the cluster's end untested.
    """
    if search.empty or not keys:
        return [], Counters(0, 0, 0)
    high = threshold if threshold_above is None else threshold_above
    lo, hi = search.bounds()
    i, taken, scans, jumps = bisect_left(keys, lo), [], 0, 0
    n = len(keys)
    while i < n and keys[i] <= hi:
        key = keys[i]
        y = search.mismatch(key)
        if y == 0:
            end = search.cluster_end(key) if cluster_end else key
            while i < n and keys[i] <= end:
                taken.append(i)
                i += 1
        elif abs(y) <= (high if y > 0 else threshold):
            scans += 1
            i += 1
        else:
            jumps += 1
            target = search.hint(key, y)
            if target is None:
                break
            i = bisect_left(keys, target, i + 1)
    return taken, Counters(len(taken), scans, jumps)


class Cursor:
    """A walk over batches of sorted keys; between batches it remembers where the last jump leads.

    Rows between two jumps need no loop: what was matched, scanned and tested follows from sums.
    """

    def __init__(self, threshold: int, threshold_above: int | None, cluster_end: bool):
        self.below, self.above = threshold, threshold if threshold_above is None else threshold_above
        self.cluster_end = cluster_end
        self.matched = self.scans = self.jumps = self.tests = 0
        self.target: list[int] | None = None
        self.cluster: tuple | None = None

    @staticmethod
    def seek(keys: list[np.ndarray], target: list[int], start: int) -> int:
        """The first place from ``start`` on whose key is at or above ``target``, limb by limb."""
        lo, hi = start, len(keys[0])
        for k, x in zip(keys, target, strict=True):
            part = k[lo:hi]
            lo, hi = lo + int(np.searchsorted(part, x, "left")), lo + int(np.searchsorted(part, x, "right"))
            if lo == hi:
                break
        return lo

    def walk(self, keys: list[np.ndarray], mismatch: np.ndarray, following: list[np.ndarray], cluster: list[np.ndarray]) -> None:
        """``following`` holds the limbs of the next matches, ``cluster`` those of each key's cluster."""
        size = len(mismatch)
        stops = np.flatnonzero(np.where(mismatch > 0, mismatch > self.above, -mismatch > self.below))
        took = mismatch == 0
        entered = took.copy()
        if self.cluster_end and size:  # a match in the cluster of the match before is taken untested
            same = np.logical_and.reduce([c[1:] == c[:-1] for c in cluster])
            entered[1:] &= ~(same & took[:-1])
            entered[0] &= self.cluster != tuple(int(c[0]) for c in cluster)
        sums = [np.concatenate(([0], np.cumsum(x))) for x in (took, ~took, entered)]
        at = 0 if self.target is None else self.seek(keys, self.target, 0)
        while at < size:
            k = int(np.searchsorted(stops, at))
            end = int(stops[k]) if k < len(stops) else size
            matched, scans, tests = (int(x[end] - x[at]) for x in sums)
            self.matched, self.scans, self.tests = self.matched + matched, self.scans + scans, self.tests + scans + tests
            self.target = None
            if end == size:
                break
            self.jumps, self.tests = self.jumps + 1, self.tests + 1
            self.target = [int(h[end]) for h in following]
            at = self.seek(keys, self.target, end + 1)
        if size:
            self.cluster = tuple(int(c[-1]) for c in cluster) if took[-1] else None


def cursor_counters(store: KeyedStore, search: Search, threshold: int, threshold_above: int | None = None, cluster_end: bool = False) -> DataFrame:
    """``slice``, ``matched``, ``scans``, ``jumps``, ``tests`` and ``hints`` (calls of the matcher) of each slice.

    Slices are read as they were written, sorted by key, without an exchange; a task holds one batch at
    a time. Slices run in parallel, and the scan ends with the slice.
    """
    ship(store.spark)
    names, limbs = store.layout.key_columns, store.layout.limb_count
    following = [f"h{i}" for i in range(limbs)]
    inside, key = marked(store.data, names, search, ["slice"], "y", following), [F.col(k) for k in names]
    low = tail(search.mask) if search.mask else search.n
    cluster = [F.shiftright(k, min(max(low - (limbs - 1 - j) * 62, 0), 62)).alias(f"c{j}") for j, k in enumerate(key)]
    rows = inside.select(F.col("slice").cast("int").alias("slice"), *key, "y", *(F.coalesce(h, F.lit(-1)).alias(h) for h in following), *cluster)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number, cursor, last = None, None, None
        out: list[tuple] = []

        def close() -> None:
            if cursor is not None:
                out.append((number, cursor.matched, cursor.scans, cursor.jumps, cursor.tests, cursor.jumps))

        for batch in batches:
            held = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
            edges = np.flatnonzero(np.diff(held[0])) + 1
            for part in np.split(np.arange(batch.num_rows), edges):
                if not len(part):
                    continue
                a, b = int(part[0]), int(part[-1]) + 1
                keys = [x[a:b] for x in held[1 : 1 + limbs]]
                begins = [int(k[0]) for k in keys]
                if number != int(held[0][a]) or (last is not None and begins < last):  # another slice, or another run of it
                    close()
                    number, cursor = int(held[0][a]), Cursor(threshold, threshold_above, cluster_end)
                last = [int(k[-1]) for k in keys]
                cursor.walk(keys, held[1 + limbs][a:b], [x[a:b] for x in held[2 + limbs : 2 + 2 * limbs]], [x[a:b] for x in held[2 + 2 * limbs :]])
        close()
        columns_ = list(zip(*out, strict=True)) if out else [[]] * 6
        yield pa.RecordBatch.from_arrays([pa.array(columns_[0], pa.int32()), *(pa.array(c, pa.int64()) for c in columns_[1:])], ["slice", "matched", "scans", "jumps", "tests", "hints"])

    counted = ("matched", "scans", "jumps", "tests", "hints")
    walked = rows.mapInArrow(run, "slice int, " + ", ".join(f"{c} bigint" for c in counted))
    of_slice = walked.groupBy("slice").agg(*(F.sum(c).alias(c) for c in counted))
    return store.catalog.select("slice").join(of_slice, "slice", "left").na.fill(0)  # no row between the bounds: nothing done


def marked(df: DataFrame, key_columns: list[str], search: Search, others: list[str], mismatch: str, following: list[str]) -> DataFrame:
    """Rows within the bounding interval: ``others``, the key, ``mismatch`` (signed) and ``following`` (limbs of the next match)."""
    if search.empty:
        none = [F.lit(None).cast("bigint").alias(h) for h in following]
        return df.where(F.lit(False)).select(*others, *key_columns, F.lit(0).alias(mismatch), *none)
    inside = df.where(columns.within([F.col(k) for k in key_columns], *search.bounds())).select(*others, *key_columns)
    return columns.with_next_match(inside, key_columns, search, mismatch, following)


def crawl_counters(df: DataFrame, key_columns: list[str], search: Search) -> DataFrame:
    """``matched``, ``scans``, ``jumps`` of the full scan between the bounds: a pushed filter and one aggregation."""
    keys = [F.col(k) for k in key_columns]
    inside = df.where(columns.within(keys, *search.bounds())) if not search.empty else df.where(F.lit(False))
    hit = columns.match(keys, search)
    return inside.agg(F.count_if(hit).alias("matched"), F.count_if(~hit).alias("scans"), F.lit(0).cast("bigint").alias("jumps"))


def leap_counters(df: DataFrame, key_columns: list[str], search: Search) -> DataFrame:
    """``matched``, ``scans``, ``jumps`` of a jump at every mismatch: as many jumps as there are gaps with a row."""
    following = [f"h{i}" for i in range(len(key_columns))]
    rows = marked(df, key_columns, search, [], "y", following)
    of_gap = [F.when(F.col("y") != 0, F.col(h)).alias(h) for h in following]  # all matches are one group
    gaps = rows.groupBy(*of_gap, (F.col("y") == 0).alias("hit")).agg(F.count(F.lit(1)).alias("m"))
    return gaps.agg(F.coalesce(F.sum(F.when(F.col("hit"), F.col("m"))), F.lit(0)).alias("matched"), F.lit(0).cast("bigint").alias("scans"), F.count_if(~F.col("hit")).alias("jumps"))


def declarative_counters(df: DataFrame, key_columns: list[str], search: Search, thresholds: list[int]) -> DataFrame:
    """``threshold``, ``matched``, ``scans``, ``jumps`` for every threshold, from one marking of the distinct keys.

    All rows are one scan (no slices). ``df`` has the key columns.
    """
    following = [f"h{i}" for i in range(len(key_columns))]
    key = F.struct(*key_columns)
    counted = df.groupBy(*key_columns).agg(F.count(F.lit(1)).alias("m"))
    rows = marked(counted, key_columns, search, ["m"], "y", following)
    each = rows.withColumn("threshold", F.explode(F.array(*map(F.lit, thresholds))))
    first = F.min(F.when(F.abs("y") > F.col("threshold"), key)).over(Window.partitionBy("threshold", *following))
    scanned = (F.col("y") != 0) & (F.col("first").isNull() | (key < F.col("first")))
    gaps = each.withColumn("first", first).groupBy("threshold", *following).agg(F.sum(F.when(F.col("y") == 0, F.col("m"))).alias("matched"), F.sum(F.when(scanned, F.col("m"))).alias("scans"), F.max(F.col("first").isNotNull().cast("int")).alias("jump"))
    got = gaps.groupBy("threshold").agg(F.sum("matched").alias("matched"), F.sum("scans").alias("scans"), F.sum("jump").alias("jumps"))
    ts = df.sparkSession.createDataFrame([(t,) for t in thresholds], "threshold int")
    zero = lambda c: F.coalesce(F.col(c), F.lit(0)).cast("bigint").alias(c)
    return ts.join(got, "threshold", "left").select("threshold", zero("matched"), zero("scans"), zero("jumps"))


def race(store: KeyedStore, search: Search, ratio: float, thresholds: dict[str, int]) -> DataFrame:
    """``strategy``, ``threshold``, counters and cost for named thresholds."""
    got = declarative_counters(store.data, store.layout.key_columns, search, sorted(set(thresholds.values())))
    names = store.spark.createDataFrame(list(thresholds.items()), "strategy string, threshold int")
    return names.join(got, "threshold").select("strategy", "threshold", "matched", "scans", "jumps", (F.col("scans") * ratio + F.col("jumps")).alias("cost"))


def average_counters(df: DataFrame, mask: int, n: int, threshold: int, key: str = "k0") -> DataFrame:
    """Totals over all patterns of a point mask on one-limb keys: ``leap_jumps``, ``crawl_scans``, ``hybrid_jumps``, ``hybrid_scans``.

    Keys count within each pattern's bounding interval. See :func:`averages`.
    """
    got = averages(df, {mask: threshold}, n, key)[mask]
    return df.sparkSession.createDataFrame([tuple(map(Decimal, got.values()))], ", ".join(f"{c} decimal(38,0)" for c in got))


def averages(df: DataFrame, thresholds: dict[int, int], n: int, key: str = "k0") -> dict[int, dict[str, int]]:
    """:func:`average_counters` of several masks, each with its threshold, in one pass over the sorted keys.

    No row meets the patterns one by one: how many patterns have a gap with a row between two
    neighbouring keys, and for how many a key is scanned, follow from the keys' bits. A task gives its
    totals and its ends, and what lies between the tasks' keys is added by the driver.
    """
    if n > LIMB:
        raise ValueError(f"averages need keys of one limb, these have {n} bits")
    ship(df.sparkSession)
    names = ("first", "last", "leap", "hybrid", "crawl", "scans", "open", "before")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        totals = {mask: PatternTotals(mask, n, t) for mask, t in thresholds.items()}
        for batch in batches:
            for x in totals.values():
                x.add(batch.column(0).to_numpy(), batch.column(1).to_numpy())
        out = [(mask, *(getattr(x, c) for c in names)) for mask, x in totals.items() if x.first is not None]
        columns_ = list(zip(*out, strict=True)) if out else [[]] * (1 + len(names))
        yield pa.RecordBatch.from_arrays([pa.array(map(Decimal, c), pa.decimal128(38, 0)) for c in columns_], ["mask", *names])  # two attributes have more patterns than a long has room for, times rows

    counted = df.groupBy(F.col(key).alias("k")).agg(F.count(F.lit(1)).alias("m"))
    tasks = counted.repartitionByRange("k").sortWithinPartitions("k").mapInArrow(run, ", ".join(f"{c} decimal(38,0)" for c in ("mask", *names))).collect()  # a row for each task and mask
    of_mask: dict[int, list] = {mask: [] for mask in thresholds}
    for r in tasks:
        of_mask[int(r["mask"])].append({c: int(r[c]) for c in names})
    return {mask: PatternTotals.joined(sorted(of_mask[mask], key=lambda r: r["first"]), mask, n, t) for mask, t in thresholds.items()}


def filled(x: np.ndarray) -> np.ndarray:
    """All bits from the highest set one down."""
    for k in (1, 2, 4, 8, 16, 32):
        x = x | x >> k
    return x


def total(x: np.ndarray, m: np.ndarray | None = None) -> int:
    """The exact sum of numbers from 0 to 2^63, each ``m`` times, whatever its size."""
    if m is not None and int(m.sum()) >> 32:
        return int((x.astype(object) * m).sum())
    high, low = x >> 31, x & 0x7FFFFFFF
    return (int((high if m is None else high * m).sum()) << 31) + int((low if m is None else low * m).sum())


class Gather:
    """``functions.bits.gather`` on arrays of keys of ``n`` bits: their masked bits from a table for every twelve."""

    WIDTH = 12

    def __init__(self, mask: int, n: int):
        self.tables = []
        for shift in range(0, n, self.WIDTH):
            piece, below = mask >> shift & ones(self.WIDTH), (mask & ones(shift)).bit_count()
            if piece:
                chunk, table = np.arange(1 << self.WIDTH, dtype=np.int64), np.zeros(1 << self.WIDTH, np.int64)
                for j in range(self.WIDTH):
                    if piece >> j & 1:
                        table |= (chunk >> j & 1) << below
                        below += 1
                self.tables.append((shift, table))

    def __call__(self, keys: np.ndarray) -> np.ndarray:
        out = np.zeros(len(keys), np.int64)
        for shift, table in self.tables:
            out |= table[keys >> shift & ones(self.WIDTH)]
        return out


class PatternTotals:
    """Counters over all patterns of a mask, from batches of distinct sorted keys and their numbers of rows.

    The gap before a match is what lies after the match before it, whose free bits are the number less
    by one. Let ``j`` be the free bit that is raised from one to the other: keys of the gap share the
    bits above ``j`` with both, and stand above the one (with bit j zero) or below the other (with it one).
    Of the keys without bit j the greatest decides whether a pattern's gap has one, of those with it the
    least; where both are there, they are neighbours. Mismatches above the threshold stand in the middle
    of a gap, and are the same question about keys without the bits up to the threshold.

    No bit is looked at by itself: a key stands above the patterns whose number is less than its masked
    bits down to its next free zero (below: to its next free one), so that the patterns of all ``j`` in
    turn add up to the number that the masked bits below the first of them make.
    """

    def __init__(self, mask: int, n: int, threshold: int):
        self.mask, self.n, self.t = mask, n, min(threshold, n)
        self.free = ones(n) & ~mask
        self.number, self.senior_number = Gather(mask, n), Gather(mask >> self.t, n - self.t)
        self.first: int | None = None
        self.last = self.before = -1
        #: Scans of the keys whose senior bits are those of the first key: whether they count depends on the key before that.
        self.open = 0
        self.leap = self.hybrid = self.crawl = self.scans = 0

    @staticmethod
    def gaps(a: np.ndarray, b: np.ndarray, free: int, n: int, number: Gather) -> int:
        """Gaps, over all patterns, with a key that are decided by the neighbours ``a`` and ``b``; -1 stands for no key."""
        both = (a >= 0) & (b >= 0)
        apart = filled(np.where(both, a ^ b, 0))
        below = np.where(both, apart >> 1, np.int64(ones(n)))  # the bits below the highest in which they differ
        b = np.where(b >= 0, b, 0)  # no free one, as -1 has no free zero
        zero, one = filled(~a & free & below) >> 1, filled(b & free & below) >> 1
        out = total(number(a & zero)) + total(number(~b & one))
        raised = (apart & ~below & free & -both.astype(np.int64)) != 0  # that bit is free: both decide on one gap
        a, b, below, zero, one = (x[raised] for x in (a, b, below, zero, one))
        return out + total(np.minimum(number(a & below & ~zero) + number(~b & below & ~one), number(below) + 1))

    def leaps(self, a: np.ndarray, b: np.ndarray) -> int:
        return self.gaps(a, b, self.free, self.n, self.number)

    def long_leaps(self, a: np.ndarray, b: np.ndarray) -> int:
        """:meth:`leaps` over mismatches above the threshold, from the keys' bits above it."""
        return self.gaps(a, b, self.free >> self.t, self.n - self.t, self.senior_number) << (self.mask & ones(self.t)).bit_count()

    def add(self, keys: np.ndarray, m: np.ndarray) -> None:
        if not len(keys):
            return
        senior = keys >> self.t
        begins = np.append(self.first is None or senior[0] != self.last >> self.t, senior[1:] != senior[:-1])
        former = np.append(np.int64(self.last if self.first is not None else -1), keys[:-1])
        inner = 0 if self.first is not None else 1
        self.leap += self.leaps(former[inner:], keys[inner:])
        known = begins & (former >= 0)
        self.hybrid += self.long_leaps(former[known] >> self.t, senior[known])
        place = np.maximum.accumulate(np.where(begins, np.arange(len(keys)), -1))
        before = np.where(place >= 0, np.where(former[place] >= 0, former[place] >> self.t, -1), self.before)
        self.first = int(keys[0]) if self.first is None else self.first
        self.last, self.before = int(keys[-1]), int(before[-1])
        crawl, sure, rest = self.scanned(keys)
        self.crawl += total(crawl, m)
        empty = (before >= 0) & self.empty_before(senior, before)
        self.scans += total(sure, m) + total(rest[empty], m[empty])
        self.open += total(rest[before < 0], m[before < 0])

    def scanned(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """For how many patterns a key is scanned by crawl, by hybrid, and by hybrid if no mismatch of its gap is above the threshold."""
        up_to, used = ones(self.t), keys & self.free
        zero, one, junior = filled(~keys & self.free) >> 1, filled(used) >> 1, filled(used & up_to) >> 1  # bits below the first free zero, one, and one below the threshold
        return self.number((keys & zero) | (~keys & one)), self.number((keys & zero & up_to) | (~keys & junior)), self.number(~keys & one & up_to & ~junior)

    def empty_before(self, senior: np.ndarray, before: np.ndarray) -> np.ndarray:
        """Whether no key without its junior bits stands in the gap before ``senior``; ``before`` is the next lower one, -1 for none."""
        free = senior & np.int64(self.free >> self.t)
        low = free & -free
        return before <= ((senior ^ low) | ((low - 1) & np.int64(self.free >> self.t)))

    @classmethod
    def joined(cls, tasks: list, mask: int, n: int, threshold: int) -> dict[str, int]:
        """The totals of tasks in key order."""
        own, last, before = cls(mask, n, threshold), -1, -1
        for r in tasks:
            own.leap, own.hybrid, own.crawl, own.scans = own.leap + r["leap"], own.hybrid + r["hybrid"], own.crawl + r["crawl"], own.scans + r["scans"]
            senior, former = r["first"] >> own.t, last >> own.t if last >= 0 else -1
            own.leap += own.leaps(np.array([last]), np.array([r["first"]]))
            if former != senior:
                own.hybrid += own.long_leaps(np.array([former]), np.array([senior]))
                before = former
            own.scans += r["open"] * int(own.empty_before(np.array([senior]), np.array([before]))[0])
            last, before = r["last"], r["before"] if r["before"] >= 0 else before
        if tasks:
            end = np.array([-1])
            own.leap += own.leaps(np.array([last]), end)
            own.hybrid += own.long_leaps(np.array([last >> own.t]), end)
        return {"leap_jumps": own.leap, "crawl_scans": own.crawl, "hybrid_jumps": own.hybrid, "hybrid_scans": own.scans}


def point_counters(df: DataFrame, search: Search, thresholds: list[int], key: str = "k0") -> DataFrame:
    """:func:`declarative_counters` for point searches on one-limb keys, from one pass over sorted keys."""
    got = points_counters(df, {"": (search, thresholds)}, key)[""]
    return df.sparkSession.createDataFrame([(t, *got[t]) for t in thresholds], "threshold int, matched bigint, scans bigint, jumps bigint")


def in_order(df: DataFrame, key: str, kind: type, wanted: list[tuple]) -> list:
    """The rows that walkers of a ``kind``, one for each of ``wanted``, give for every run of sorted keys: runs that don't overlap.

    The data of a store are passed as they were written. Rows in another order are sorted first.
    """
    ship(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        of_slice, walks, out = None, [], []
        for batch in batches:
            keys = batch.column(0).to_numpy()
            slices = batch.column(1).to_numpy()
            cuts = np.flatnonzero((np.diff(keys) < 0) | (np.diff(slices) != 0)) + 1
            for k, number in zip(np.split(keys, cuts), slices[np.append(0, cuts)] if len(keys) else [], strict=False):
                if not walks or number != of_slice or k[0] < walks[0].last:  # another run of sorted keys
                    out += [x.row() for x in walks]
                    of_slice, walks = number, [kind(*x) for x in wanted]
                marks: dict[int, tuple] = {}
                for x in walks:
                    x.add(k, marks)
        out += [x.row() for x in walks]
        yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (zip(*out, strict=True) if out else [[]] * len(kind.COLUMNS))], kind.COLUMNS)

    def runs(rows: DataFrame) -> list:
        return rows.mapInArrow(run, ", ".join(f"{c} bigint" for c in kind.COLUMNS)).collect()  # some rows for each task and slice

    if "slice" in df.columns:
        found = runs(df.select(F.col(key).cast("bigint"), F.col("slice").cast("bigint")))
        ends = sorted((r["begin"], r["last"]) for r in found[:: len(wanted)])
        if all(a[1] <= b[0] for a, b in zip(ends, ends[1:])):
            return found
    return runs(df.select(F.col(key).cast("bigint").alias("k")).repartitionByRange("k").sortWithinPartitions("k").select("k", F.lit(0).cast("bigint")))


def points_counters(df: DataFrame, searches: dict[str, tuple[Search, list[int]]], key: str = "k0") -> dict[str, dict[int, tuple[int, int, int]]]:
    """``matched``, ``scans`` and ``jumps`` by threshold of several point searches, in one pass over the keys in order.

    The data of a store are passed as they were written; tasks give the totals of whole gaps and the
    parts of the gaps at their ends, which the driver puts together. Rows in another order are sorted first.
    """
    wanted = [(i, *search.point, search.n, t) for i, (search, thresholds) in enumerate(searches.values()) for t in sorted(set(thresholds))]
    found = in_order(df, key, PointRun, wanted)
    out: dict[str, dict[int, tuple[int, int, int]]] = {}
    for i, (name, (_, thresholds)) in enumerate(searches.items()):
        out[name] = {t: PointRun.joined([r for r in found if (r["search"], r["threshold"]) == (i, t)]) for t in thresholds}
    return out


def region_sigmas(df: DataFrame, masks: list[int], n: int, key: str = "k0") -> dict[int, float]:
    """``costs.region_sigma`` of several masks, in one pass over the keys in order; masks with the same tail have the same regions."""
    tails = sorted({tail(mask) for mask in masks})
    found = in_order(df, key, RegionRun, [(t,) for t in tails])
    sigma = {t: costs.sigma_of(*RegionRun.joined([r for r in found if r["tail"] == t]), n - t) for t in tails}
    return {mask: sigma[tail(mask)] for mask in masks}


class RegionRun:
    """Rows and the sum of squares of the regions' numbers of rows over a run of sorted keys; other runs may hold rows of its first and last region."""

    COLUMNS = ("tail", "begin", "last", "rows", "high", "low", "region0", "rows0", "region1", "rows1")

    def __init__(self, tail: int):
        self.tail = tail
        self.begin: int | None = None
        self.last = -1
        self.rows = self.squares = 0
        #: The first region, and the one that the keys so far end in, with their numbers of rows.
        self.opening: tuple[int, int] | None = None
        self.region: tuple[int, int] | None = None

    def row(self) -> tuple:
        ends = [*(self.opening or self.region or (-1, 0)), *(self.region if self.opening and self.region else (-1, 0))]
        return (self.tail, self.begin, self.last, self.rows, self.squares >> 62, self.squares & ones(62), *ends)

    def add(self, keys: np.ndarray, marks: dict[int, tuple]) -> None:
        if not len(keys):
            return
        self.begin = int(keys[0]) if self.begin is None else self.begin
        self.last, self.rows = int(keys[-1]), self.rows + len(keys)
        regions = keys >> self.tail
        begins = np.flatnonzero(np.append(True, regions[1:] != regions[:-1]))
        size, at = np.diff(np.append(begins, len(keys))), regions[begins]
        if self.region and self.region[0] == at[0]:
            size[0] += self.region[1]
        elif self.region:
            size, at = np.append(self.region[1], size), np.append(self.region[0], at)
        if len(at) > 1 and self.opening is None:
            self.opening = (int(at[0]), int(size[0]))
            size, at = size[1:], at[1:]
        self.squares += total(size[:-1], size[:-1])
        self.region = (int(at[-1]), int(size[-1]))

    @staticmethod
    def joined(runs: list) -> tuple[int, int]:
        """Rows and squares of runs that don't overlap."""
        ends: Counter = Counter()
        for r in runs:
            ends.update({r["region0"]: r["rows0"]})
            ends.update({r["region1"]: r["rows1"]})
        return sum(r["rows"] for r in runs), sum((r["high"] << 62) + r["low"] for r in runs) + sum(m * m for m in ends.values())


class PointRun:
    """Counters of a point search at a threshold over a run of sorted keys.

    In a gap, in key order: mismatches up to the threshold above the former match, mismatches above the
    threshold, mismatches up to it below the next match. The first are scanned, and the last too where
    none is above it; else the first of these is where the search jumps.
    """

    COLUMNS = ("search", "threshold", "begin", "last", "matched", "scans", "jumps", "h0", "former0", "latter0", "over0", "h1", "former1", "latter1", "over1")

    def __init__(self, number: int, mask: int, pattern: int, n: int, threshold: int):
        self.number, self.mask, self.pattern, self.n, self.t = number, mask, pattern, n, threshold
        self.begin: int | None = None
        self.last = -1
        self.matched = self.scans = self.jumps = 0
        #: The first gap, and the one that the keys so far end in: next match, scanned rows on both sides, and rows above the threshold.
        self.opening: tuple[int, int, int, int] | None = None
        self.gap: tuple[int, int, int, int] | None = None

    def row(self) -> tuple:
        ends = [*(self.opening or self.gap or (-1, 0, 0, 0)), *(self.gap if self.opening and self.gap else (-1, 0, 0, 0))]
        return (self.number, self.t, self.begin, self.last, self.matched, self.scans, self.jumps, *ends)

    def mark(self, keys: np.ndarray) -> tuple:
        """Of the keys within the bounds: mismatch, next match, and whether they stand above the match before."""
        free = ((1 << self.n) - 1) & ~self.mask
        k = keys[np.searchsorted(keys, self.pattern, "left") : np.searchsorted(keys, self.pattern | free, "right")]
        differs = (k & np.int64(self.mask)) ^ np.int64(self.pattern)
        y = np.frexp(differs.astype(np.float64))[1].astype(np.int64)
        y -= (differs > 0) & ((differs >> np.maximum(y - 1, 0)) == 0)  # rounded up to the next power
        fail = np.where(y > 0, np.int64(1) << np.maximum(y - 1, 0), 0)
        above = (k & fail) != 0
        up_to = fail | np.maximum(fail - 1, 0)
        open_bits = ~k & np.int64(free) & ~up_to
        grow = np.where(above, open_bits & -open_bits, fail)  # within the bounds there is one
        following = (k & ~(grow | np.maximum(grow - 1, 0))) | grow | (np.maximum(grow - 1, 0) & np.int64(self.pattern))
        return y, np.where(y > 0, following, k), above

    def add(self, keys: np.ndarray, marks: dict[int, tuple]) -> None:
        """``marks`` keeps what the thresholds of a search share."""
        if not len(keys):
            return
        self.begin = int(keys[0]) if self.begin is None else self.begin
        self.last = int(keys[-1])
        if self.number not in marks:
            marks[self.number] = self.mark(keys)
        y, h, above = marks[self.number]
        if not len(y):
            return
        begins = np.flatnonzero(np.append(True, h[1:] != h[:-1]))
        scanned = (y > 0) & (y <= self.t)
        former, latter, over = (np.add.reduceat(x.astype(np.int64), begins) for x in (scanned & above, scanned & ~above, y > self.t))
        self.matched += int((y == 0).sum())
        if self.gap and self.gap[0] == h[0]:
            former[0], latter[0], over[0] = former[0] + self.gap[1], latter[0] + self.gap[2], over[0] + self.gap[3]
        elif self.gap:
            self.close(self.gap)
        at = h[begins]
        if len(at) > 1 and self.opening is None:
            self.close(tuple(int(x[0]) for x in (at, former, latter, over)))
            at, former, latter, over = at[1:], former[1:], latter[1:], over[1:]
        self.scans += int(former[:-1].sum()) + int(latter[:-1][over[:-1] == 0].sum())
        self.jumps += int((over[:-1] > 0).sum())
        self.gap = tuple(int(x[-1]) for x in (at, former, latter, over))

    def close(self, gap: tuple[int, int, int, int]) -> None:
        """A gap that no later key of the run lies in; of the first, others may hold a part."""
        if self.opening is None:
            self.opening = gap
        else:
            self.scans += gap[1] + (0 if gap[3] else gap[2])
            self.jumps += int(gap[3] > 0)

    @staticmethod
    def joined(runs: list) -> tuple[int, int, int]:
        """``matched``, ``scans`` and ``jumps`` of runs that don't overlap."""
        matched, scans, jumps = (sum(r[c] for r in runs) for c in ("matched", "scans", "jumps"))
        gaps: dict[int, list[int]] = {}
        for r in runs:
            for side in "01":
                if r[f"h{side}"] >= 0:
                    held = gaps.setdefault(r[f"h{side}"], [0, 0, 0])
                    held[:] = [x + r[f"{c}{side}"] for x, c in zip(held, ("former", "latter", "over"), strict=True)]
        scans += sum(former + (0 if over else latter) for former, latter, over in gaps.values())
        return matched, scans, jumps + sum(over > 0 for _, _, over in gaps.values())
