"""Filters as users write them, as restrictions on keys and as exact conditions on the columns."""

from __future__ import annotations

import datetime as dt
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

from keyhop.functions.curve import Attribute, KeyLayout
from keyhop.plans.search import Restriction, Search, normal_intervals


class Filter:
    """A condition on one attribute."""

    def intervals(self, a: Attribute) -> list[tuple[int, int]]:
        raise NotImplementedError

    def column(self, c: Column) -> Column:
        raise NotImplementedError


@dataclass(frozen=True)
class Eq(Filter):
    value: object

    def intervals(self, a):
        found = a.codec.interval(self.value, self.value)
        return [found] if found else []

    def column(self, c):
        return c == F.lit(self.value)


@dataclass(frozen=True)
class Between(Filter):
    """Closed interval; None is an open end."""

    lo: object = None
    hi: object = None

    def intervals(self, a):
        found = a.codec.interval(self.lo, self.hi)
        return [found] if found else []

    def column(self, c):
        out = c.isNotNull()
        if self.lo is not None:
            out = out & (c >= F.lit(self.lo))
        if self.hi is not None:
            out = out & (c <= F.lit(self.hi))
        return out


@dataclass(frozen=True)
class In(Filter):
    values: tuple

    def intervals(self, a):
        return [x for v in self.values for x in Eq(v).intervals(a)]

    def column(self, c):
        return c.isin(*self.values)


@dataclass(frozen=True)
class NotIn(Filter):
    """All other values; null is none of them."""

    values: tuple

    def intervals(self, a):
        if not a.codec.exact:
            return [(1, a.codec.size)]
        gone = {x for v in self.values for x, _ in Eq(v).intervals(a)}
        out, start = [], 1
        for g in sorted(gone):
            out.append((start, g - 1))
            start = g + 1
        return [*out, (start, a.codec.size)]

    def column(self, c):
        return ~c.isin(*self.values)


@dataclass(frozen=True)
class Prefix(Filter):
    """Strings that begin with ``text``."""

    text: str

    def intervals(self, a):
        return [(i + 1, i + 1) for i, v in enumerate(a.codec.values) if v.startswith(self.text)]

    def column(self, c):
        return c.startswith(self.text)


@dataclass(frozen=True)
class IsNull(Filter):
    def intervals(self, a):
        return [(0, 0)]

    def column(self, c):
        return c.isNull()


@dataclass(frozen=True)
class NotNull(Filter):
    def intervals(self, a):
        return [(1, a.codec.size)]

    def column(self, c):
        return c.isNotNull()


@dataclass(frozen=True)
class AnyOf(Filter):
    """A union of conditions on the same attribute."""

    filters: tuple[Filter, ...]

    def intervals(self, a):
        return [x for f in self.filters for x in f.intervals(a)]

    def column(self, c):
        out = F.lit(False)
        for f in self.filters:
            out = out | f.column(c)
        return out


def search_of(layout: KeyLayout, filters: dict[str, Filter]) -> Search:
    """The search for all of ``filters``, by attribute name."""
    out = []
    for name, f in filters.items():
        out.append(Restriction(layout.mask(name), normal_intervals(f.intervals(layout.attribute(name)))))
    return Search(layout.n, tuple(out))


def condition(layout: KeyLayout | None, filters: dict[str, Filter]) -> Column:
    """The same as an exact condition on the attributes' columns, in a form that Parquet's statistics can test."""
    out = F.lit(True)
    for name, f in filters.items():
        kind = layout.attribute(name).codec if layout else None
        if kind is not None and kind.kind == "days":
            out = out & _ranged(f, F.col(name), lambda v: (F.lit(v), F.lit(v + dt.timedelta(days=1))), lambda c: F.to_date(c))
        elif kind is not None and kind.kind == "raw" and kind.width != 1.0:
            half = kind.width / 2
            out = out & _ranged(f, F.col(name), lambda v, half=half: (F.lit(v - half), F.lit(v + half)), lambda c: F.round(c, 2))
        else:
            out = out & f.column(F.col(name))
    return out


def _ranged(f: Filter, c: Column, ends: Callable, value: Callable[[Column], Column]) -> Column:
    """A filter on rounded values as bounds on the stored ones: ``ends`` gives the half-open interval that rounds to a value."""
    if isinstance(f, Eq) and f.value is not None:
        lo, hi = ends(f.value)
        return (c >= lo) & (c < hi)
    if isinstance(f, Between):
        out = c.isNotNull()
        if f.lo is not None:
            out = out & (c >= ends(f.lo)[0])
        if f.hi is not None:
            out = out & (c < ends(f.hi)[1])
        return out
    if isinstance(f, In) and f.values and all(v is not None for v in f.values):
        out = F.lit(False)
        for v in f.values:
            out = out | _ranged(Eq(v), c, ends, value)
        return out
    if isinstance(f, AnyOf):
        out = F.lit(False)
        for x in f.filters:
            out = out | _ranged(x, c, ends, value)
        return out
    return f.column(value(c))
