"""Attribute codecs and generalised z-curve layouts of a composite key.

A codec maps a column to consecutive codes in value order; code 0 stands for null. A layout assigns
every code bit a key bit and keeps the order of the bits of an attribute, so that a condition on an
attribute becomes one on the bits under its mask. Keys wider than a limb are split in limbs, senior
first, each a non-negative long, so that row order is the lexicographic order of the limb columns.
"""

from __future__ import annotations

import datetime as dt
import json
import math
from collections.abc import Iterable
from dataclasses import asdict, dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from keyhop.functions.bits import LIMB, limbs, ones


@dataclass(frozen=True)
class Codec:
    """``kind``: raw (integers from ``lo``), days (dates from ``lo``), bins (width ``width`` from ``lo``) or dict."""

    kind: str
    lo: float = 0
    width: float = 1.0
    values: tuple = ()
    size: int = 0

    @property
    def exact(self) -> bool:
        return self.kind != "bins"

    def column(self, c: Column) -> Column:
        """Code of a column's value; null gives 0."""
        if self.kind == "raw":
            code = F.round(c - F.lit(self.lo)).cast("bigint") + 1 if self.width == 1.0 else F.round((c - F.lit(self.lo)) / self.width).cast("bigint") + 1
        elif self.kind == "days":
            code = F.datediff(c, F.lit(_day(int(self.lo)))).cast("bigint") + 1
        elif self.kind == "bins":
            code = F.least(F.greatest(F.floor((c - F.lit(self.lo)) / self.width), F.lit(0)), F.lit(self.size - 1)).cast("bigint") + 1
        else:
            code = F.array_position(F.array(*map(F.lit, self.values)), c)
        return F.coalesce(code, F.lit(0).cast("bigint"))

    def code(self, value) -> float | None:
        """Code of a value, not rounded for a value between codes; None for an unknown dictionary value."""
        if self.kind == "dict":
            return self.values.index(value) + 1 if value in self.values else None
        if self.kind == "days":
            d = value if isinstance(value, dt.date) and not isinstance(value, dt.datetime) else dt.date.fromisoformat(str(value)[:10])
            return d.toordinal() - self.lo + 1
        x = (value - self.lo) / self.width + 1
        if self.kind == "bins":
            return min(max(math.floor(x), 1), self.size)
        return round(x) if abs(x - round(x)) < 1e-6 else x

    def interval(self, lo, hi) -> tuple[int, int] | None:
        """Codes whose values lie within [lo, hi] (None: open end); for bins those that may hold such values."""
        if self.kind == "dict":
            inside = [i + 1 for i, v in enumerate(self.values) if (lo is None or v >= lo) and (hi is None or v <= hi)]
            return (inside[0], inside[-1]) if inside else None
        a = 1 if lo is None else max(1, math.ceil(self.code(lo)))
        b = self.size if hi is None else min(self.size, math.floor(self.code(hi)))
        return (a, b) if a <= b else None


def _day(ordinal: int) -> dt.date:
    return dt.date.fromordinal(ordinal)


@dataclass(frozen=True)
class Attribute:
    """A dimension: its column, codec and number of key bits (room for all codes and the null code)."""

    name: str
    codec: Codec

    @property
    def bits(self) -> int:
        return max(1, self.codec.size.bit_length())


@dataclass
class KeyLayout:
    """Which key bit (0 the lowest) holds which code bit of which attribute."""

    attributes: list[Attribute]
    place: dict[str, list[int]] = field(default_factory=dict)  # per attribute: key bit of each code bit, lowest first

    @property
    def n(self) -> int:
        return sum(a.bits for a in self.attributes)

    @property
    def limb_count(self) -> int:
        return max(1, -(-self.n // LIMB))

    @property
    def key_columns(self) -> list[str]:
        return [f"k{i}" for i in range(self.limb_count)]

    def attribute(self, name: str) -> Attribute:
        return next(a for a in self.attributes if a.name == name)

    def mask(self, name: str) -> int:
        """The attribute's bits in the key."""
        return sum(1 << p for p in self.place[name])

    @classmethod
    def _from_order(cls, attributes: list[Attribute], order: Iterable[str]) -> KeyLayout:
        """``order``: for each key bit from the senior end the attribute that gives its next senior bit."""
        out = cls(attributes, {a.name: [] for a in attributes})
        seq = list(order)
        for i, name in enumerate(seq):
            out.place[name].insert(0, len(seq) - 1 - i)
        return out

    @classmethod
    def odometer(cls, attributes: list[Attribute]) -> KeyLayout:
        """Attributes one after another, the first the most senior."""
        return cls._from_order(attributes, [a.name for a in attributes for _ in range(a.bits)])

    @classmethod
    def blocked(cls, attributes: list[Attribute], k: int) -> KeyLayout:
        """Round-robin from the senior end, ``k`` bits of each attribute at a time, by decreasing cardinality."""
        ranked = sorted(attributes, key=lambda a: (-a.bits, -a.codec.size, a.name))
        left = {a.name: a.bits for a in ranked}
        order: list[str] = []
        while any(left.values()):
            for a in ranked:
                take = min(k, left[a.name])
                order += [a.name] * take
                left[a.name] -= take
        return cls._from_order(attributes, order)

    @classmethod
    def interleave(cls, attributes: list[Attribute], align: str = "senior") -> KeyLayout:
        """Single bits in turn; ``senior``: all heads as high as can be, ``junior``: all tails as low."""
        if align == "senior":
            return cls.blocked(attributes, 1)
        ranked = sorted(attributes, key=lambda a: (-a.bits, -a.codec.size, a.name))
        top = max(a.bits for a in ranked)
        return cls._from_order(attributes, [a.name for level in range(top, 0, -1) for a in ranked if a.bits >= level])

    @classmethod
    def custom(cls, attributes: list[Attribute], order: list[str]) -> KeyLayout:
        """Any order of attribute names from the senior end, each as often as it has bits."""
        if sorted(order) != sorted(a.name for a in attributes for _ in range(a.bits)):
            raise ValueError("each attribute must be named as often as it has bits")
        return cls._from_order(attributes, order)

    def _moves(self, name: str) -> list[tuple[int, int, int]]:
        """(code bit, key bit, length) of the runs that move together."""
        out: list[tuple[int, int, int]] = []
        for code_bit, key_bit in enumerate(self.place[name]):
            if out and out[-1][1] + out[-1][2] == key_bit and key_bit % LIMB:
                out[-1] = (out[-1][0], out[-1][1], out[-1][2] + 1)
            else:
                out.append((code_bit, key_bit, 1))
        return out

    def key_expressions(self) -> list[Column]:
        """The limbs of the key, from the attributes' columns."""
        parts: list[list[Column]] = [[] for _ in range(self.limb_count)]
        for a in self.attributes:
            code = a.codec.column(F.col(a.name))
            for code_bit, key_bit, length in self._moves(a.name):
                limb = self.limb_count - 1 - key_bit // LIMB
                piece = F.shiftright(code, code_bit).bitwiseAND(F.lit(ones(length)).cast("bigint"))
                parts[limb].append(F.shiftleft(piece, key_bit % LIMB))
        return [_any(p) for p in parts]

    def encode(self, df: DataFrame) -> DataFrame:
        """``df`` with its key columns."""
        return df.withColumns(dict(zip(self.key_columns, self.key_expressions(), strict=True)))

    def code_expression(self, name: str) -> Column:
        """An attribute's code, back from the key columns."""
        parts = []
        for code_bit, key_bit, length in self._moves(name):
            limb = self.limb_count - 1 - key_bit // LIMB
            piece = F.shiftright(F.col(f"k{limb}"), key_bit % LIMB).bitwiseAND(F.lit(ones(length)).cast("bigint"))
            parts.append(F.shiftleft(piece, code_bit))
        return _any(parts)

    def decode(self, df: DataFrame) -> DataFrame:
        """``df`` with ``code_<attribute>`` for every attribute, from its key columns."""
        return df.withColumns({f"code_{a.name}": self.code_expression(a.name) for a in self.attributes})

    def key_of(self, codes: dict[str, int]) -> int:
        """The key of codes, as a Python integer."""
        out = 0
        for name, code in codes.items():
            for bit, place in enumerate(self.place[name]):
                out |= ((code >> bit) & 1) << place
        return out

    def limbs(self, key: int) -> list[int]:
        return limbs(key, self.limb_count)

    def report(self, useful: int) -> list[dict]:
        """For each attribute: bits, mask, head, and how many of its bits are among the ``useful`` senior key bits."""
        return [{"attribute": a.name, "bits": a.bits, "head": max(self.place[a.name]) + 1, "tail": min(self.place[a.name]), "useful": sum(p >= self.n - useful for p in self.place[a.name])} for a in self.attributes]

    def to_json(self) -> str:
        return json.dumps({"attributes": [{"name": a.name, "codec": asdict(a.codec)} for a in self.attributes], "place": self.place})

    @classmethod
    def from_json(cls, text: str) -> KeyLayout:
        raw = json.loads(text)
        attributes = [Attribute(a["name"], Codec(**{**a["codec"], "values": tuple(a["codec"]["values"])})) for a in raw["attributes"]]
        return cls(attributes, {k: list(v) for k, v in raw["place"].items()})


def _any(parts: list[Column]) -> Column:
    out = parts[0] if parts else F.lit(0).cast("bigint")
    for p in parts[1:]:
        out = out.bitwiseOR(p)
    return out
