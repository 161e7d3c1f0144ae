"""Searches over composite keys: which keys match, how a key fails, and the next key that can match.

A restriction is a mask and the sorted disjoint intervals in which the masked bits, read as a number,
must lie: one value for a point, one interval for a range, several for a set, a complement or a union.
The restrictions of a search have disjoint masks.

The next match of a key raises one bit, keeps what is above it and completes what is below by the
least values. Which bit: at or above the highest bit where the key fails, the lowest zero bit that no
restriction forbids. That may be a masked bit: with sets, or with several restrictions, free bits alone
would miss keys.
"""

from __future__ import annotations

from bisect import bisect_right
from collections.abc import Iterable
from dataclasses import dataclass
from functools import cached_property

import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F

from keyhop.functions.bits import gather, gather_column, joined, limbs, ones, scatter, top_bit


def normal_intervals(intervals: Iterable[tuple[int, int]]) -> tuple[tuple[int, int], ...]:
    """Sorted, disjoint, not touching."""
    out: list[tuple[int, int]] = []
    for a, b in sorted(x for x in intervals if x[0] <= x[1]):
        if out and a <= out[-1][1] + 1:
            out[-1] = (out[-1][0], max(out[-1][1], b))
        else:
            out.append((a, b))
    return tuple(out)


@dataclass(frozen=True)
class Restriction:
    """The bits of ``mask``, as a number, lie in one of ``intervals``."""

    mask: int
    intervals: tuple[tuple[int, int], ...]

    @cached_property
    def width(self) -> int:
        return self.mask.bit_count()

    @cached_property
    def _starts(self) -> list[int]:
        return [a for a, _ in self.intervals]

    @property
    def kind(self) -> str:
        """point, range or set."""
        if len(self.intervals) == 1:
            return "point" if self.intervals[0][0] == self.intervals[0][1] else "range"
        return "set"

    @property
    def size(self) -> int:
        """Number of allowed values."""
        return sum(b - a + 1 for a, b in self.intervals)

    def allows(self, value: int) -> bool:
        i = bisect_right(self._starts, value) - 1
        return i >= 0 and value <= self.intervals[i][1]

    def least_from(self, value: int) -> int | None:
        """The smallest allowed value at or above ``value``."""
        i = bisect_right(self._starts, value) - 1
        if i >= 0 and value <= self.intervals[i][1]:
            return value
        return self.intervals[i + 1][0] if i + 1 < len(self.intervals) else None

    def match(self, key: int) -> bool:
        return self.allows(gather(key, self.mask))

    def _feasible(self, prefix: int, dropped: int) -> bool:
        """Whether an allowed value begins with ``prefix``, ``dropped`` bits being open."""
        least = self.least_from(prefix << dropped)
        return least is not None and least >> dropped == prefix

    def mismatch(self, key: int) -> int:
        """0 for a match; else the position of the highest bit at which no allowed value follows, negative where the key is below."""
        value = gather(key, self.mask)
        if self.allows(value):
            return 0
        low, high = 0, self.width  # feasible with `high` bits dropped, not with `low`
        while high - low > 1:
            mid = (low + high) // 2
            if self._feasible(value >> mid, mid):
                high = mid
            else:
                low = mid
        place = scatter(1 << (high - 1), self.mask).bit_length()
        return place if value >> (high - 1) & 1 else -place

    def accepts(self, key: int, bit: int) -> bool:
        """Whether bit ``bit`` (from 1, zero in ``key``) may be raised, everything above it kept."""
        dropped = (self.mask & ones(bit - 1)).bit_count()
        raised = gather((key | 1 << (bit - 1)) & ~ones(bit - 1), self.mask)
        return self._feasible(raised >> dropped, dropped)

    def completion(self, key: int, bit: int) -> int:
        """The masked bits of the least key above: bits from ``bit`` up as in ``key``, those below as small as allowed."""
        base = gather(key & ~ones(bit - 1), self.mask)
        return scatter(self.least_from(base), self.mask)


def Point(mask: int, value: int) -> Restriction:  # noqa: N802
    """The masked bits equal ``value``."""
    return Restriction(mask, ((value, value),))


def Range(mask: int, lo: int, hi: int) -> Restriction:  # noqa: N802
    """The masked bits lie in [lo, hi]."""
    return Restriction(mask, normal_intervals([(lo, hi)]))


def InSet(mask: int, values: Iterable[int]) -> Restriction:  # noqa: N802
    """The masked bits are one of ``values``."""
    return Restriction(mask, normal_intervals((v, v) for v in values))


@dataclass(frozen=True)
class Search:
    """All restrictions together, on keys of ``n`` bits."""

    n: int
    restrictions: tuple[Restriction, ...]

    @property
    def mask(self) -> int:
        out = 0
        for r in self.restrictions:
            out |= r.mask
        return out

    @property
    def empty(self) -> bool:
        return any(not r.intervals for r in self.restrictions)

    def match(self, key: int) -> bool:
        return all(r.match(key) for r in self.restrictions)

    def mismatch(self, key: int) -> int:
        """The mismatch with the highest bit among the restrictions."""
        return max((r.mismatch(key) for r in self.restrictions), key=abs, default=0)

    def hint(self, key: int, mismatch: int) -> int | None:
        """The least matching key above one that fails at ``mismatch``; None if there is none."""
        bit = -mismatch
        if mismatch > 0:
            for candidate in range(mismatch + 1, self.n + 1):
                if not key >> (candidate - 1) & 1 and all(r.accepts(key, candidate) for r in self.restrictions):
                    bit = candidate
                    break
            else:
                return None
        raised = (key | 1 << (bit - 1)) & ~ones(bit - 1)
        out = raised
        for r in self.restrictions:
            out |= r.completion(raised, bit)
        return out

    def next_match(self, key: int) -> int | None:
        """The least matching key at or above ``key``; None if there is none."""
        if self.empty:
            return None
        y = self.mismatch(key)
        return key if y == 0 else self.hint(key, y)

    def bounds(self) -> tuple[int, int]:
        """The least and the greatest matching key of a search that is not empty."""
        lo, hi = 0, ones(self.n) & ~self.mask
        for r in self.restrictions:
            lo |= scatter(r.intervals[0][0], r.mask)
            hi |= scatter(r.intervals[-1][1], r.mask)
        return lo, hi

    def cluster_end(self, key: int) -> int:
        """The last key of the run of matching keys that ``key``, a match, is certain to belong to."""
        low = self.mask & -self.mask
        return key | (low - 1) if low else key | ones(self.n)

    @property
    def point(self) -> tuple[int, int] | None:
        """Mask and key bits if all restrictions are points."""
        if self.empty or any(r.kind != "point" for r in self.restrictions):
            return None
        return self.mask, sum(scatter(r.intervals[0][0], r.mask) for r in self.restrictions)

    def match_column(self, key: Column) -> Column:
        """:meth:`match` of a single-limb key, without leaving code generation."""
        out = F.lit(not self.empty)
        for r in self.restrictions:
            value = gather_column(key, r.mask)
            some = [value == a if a == b else value.between(a, b) for a, b in r.intervals]
            if some:
                any_of = some[0]
                for s in some[1:]:
                    any_of = any_of | s
                out = out & any_of
        return out

    def next_match_column(self, key: Column) -> Column:
        """:meth:`next_match` of a single-limb key for points; null stands for none."""
        if self.point is None:
            raise ValueError("the column form is for points; use next_match_udf")
        return next_match_of_pattern(key, F.lit(self.point[1]).cast("bigint"), self.mask, self.n)


def failing_bit(key: Column, pattern: Column, mask: int) -> Column:
    """The highest masked bit in which a long key differs from the pattern; 0 for a match."""
    return top_bit(key.bitwiseAND(F.lit(mask).cast("bigint")).bitwiseXOR(pattern))


def next_match_of_pattern(key: Column, pattern: Column, mask: int, n: int) -> Column:
    """The next key with the pattern's bits on ``mask``, as a bit expression; null stands for none."""
    fail = failing_bit(key, pattern, mask)
    under = fail - 1
    kept = key.bitwiseAND(F.bitwise_not(fail.bitwiseOR(under)))
    low = kept.bitwiseOR(fail).bitwiseOR(pattern.bitwiseAND(under))
    open_bits = F.bitwise_not(key).bitwiseAND(F.lit(ones(n) & ~mask).cast("bigint")).bitwiseAND(F.bitwise_not(fail.bitwiseOR(under)))
    grow = open_bits.bitwiseAND(-open_bits)
    high = key.bitwiseAND(F.bitwise_not(grow.bitwiseOR(grow - 1))).bitwiseOR(grow).bitwiseOR(pattern.bitwiseAND(grow - 1))
    return F.when(fail == 0, key).when(key.bitwiseAND(fail) == 0, low).when(grow != 0, high)


def limb_list(key: int | None, count: int) -> list[int] | None:
    return None if key is None else limbs(key, count)


def next_match_udf(search: Search, limb_count: int):
    """A function of the array of limbs that gives the limbs of the next match; null stands for none."""
    @F.arrow_udf("array<bigint>")
    def run(keys: pa.Array) -> pa.Array:
        return pa.array([limb_list(search.next_match(joined(x)), limb_count) for x in keys.to_pylist()], pa.list_(pa.int64()))

    return run


def mismatch_udf(search: Search):
    """A function of the array of limbs that gives the signed mismatch."""
    @F.arrow_udf("int")
    def run(keys: pa.Array) -> pa.Array:
        return pa.array([search.mismatch(joined(x)) for x in keys.to_pylist()], pa.int32())

    return run


def crawl_intervals(search: Search, threshold: int) -> list[tuple[int, int]]:
    """The key intervals that hybrid scans at a threshold for a point: regions of that order whose senior bits match.

    There are 2^(free bits above the threshold) of them; callers keep that number small.
    """
    mask, pattern = search.point
    senior = ones(search.n) & ~ones(threshold)
    free = senior & ~mask
    fixed = pattern & mask & senior
    return [(fixed | scatter(f, free), fixed | scatter(f, free) | ones(threshold)) for f in range(1 << free.bit_count())]
