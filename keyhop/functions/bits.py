"""Bit functions on Python integers and, in the same words, on Columns of non-negative longs."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Bits of a limb: the sign and one carry bit of a long stay free.
LIMB = 62
LIMB_MASK = (1 << LIMB) - 1


def ones(n: int) -> int:
    """The ``n`` lowest bits."""
    return (1 << n) - 1


def head(mask: int) -> int:
    """Position of the highest bit, counted from 1; 0 for no bit."""
    return mask.bit_length()


def tail(mask: int) -> int:
    """Number of zeros below the lowest bit."""
    return (mask & -mask).bit_length() - 1 if mask else 0


def runs(mask: int) -> list[tuple[int, int]]:
    """(head, tail) of the maximal runs of ones, senior first."""
    out = []
    while mask:
        h = mask.bit_length()
        t = (~mask & ones(h)).bit_length()
        out.append((h, t))
        mask &= ones(t)
    return out


def gather(key: int, mask: int) -> int:
    """The masked bits of ``key`` pushed together, order kept."""
    out = 0
    for h, t in runs(mask):
        out = (out << (h - t)) | ((key >> t) & ones(h - t))
    return out


def scatter(value: int, mask: int) -> int:
    """The inverse of :func:`gather` on the bits of ``mask``."""
    out = 0
    for h, t in reversed(runs(mask)):
        out |= (value & ones(h - t)) << t
        value >>= h - t
    return out


def limbs(key: int, count: int) -> list[int]:
    """``key`` as ``count`` limbs, senior first."""
    return [(key >> (LIMB * (count - 1 - i))) & LIMB_MASK for i in range(count)]


def joined(parts: list[int]) -> int:
    """The key of limbs, senior first."""
    out = 0
    for p in parts:
        out = (out << LIMB) | p
    return out


def top_position(c: Column) -> Column:
    """Position of the highest bit of a non-negative long, counted from 1; 0 for zero."""
    return F.when(c == 0, F.lit(0)).otherwise(F.length(F.bin(c)))


def low_bit(c: Column) -> Column:
    """The lowest set bit."""
    return c.bitwiseAND(-c)


def top_bit(c: Column) -> Column:
    """The highest set bit; 0 for zero."""
    return F.when(c == 0, F.lit(0).cast("bigint")).otherwise(F.call_function("shiftleft", F.lit(1).cast("bigint"), top_position(c) - 1))


def gather_column(c: Column, mask: int) -> Column:
    """:func:`gather` on a long column."""
    out = F.lit(0).cast("bigint")
    for h, t in runs(mask):
        out = F.shiftleft(out, h - t).bitwiseOR(F.shiftright(c, t).bitwiseAND(F.lit(ones(h - t)).cast("bigint")))
    return out


def scatter_column(c: Column, mask: int) -> Column:
    """:func:`scatter` on a long column."""
    out = F.lit(0).cast("bigint")
    shift = 0
    for h, t in reversed(runs(mask)):
        out = out.bitwiseOR(F.shiftleft(F.shiftright(c, shift).bitwiseAND(F.lit(ones(h - t)).cast("bigint")), t))
        shift += h - t
    return out
