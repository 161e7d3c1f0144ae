"""The matchers as column expressions, for keys of any number of limbs and any mix of restrictions.

Nothing here leaves code generation, so mismatches and next matches can be computed for every row and
for every slice of a catalog without a Python worker. The scalar forms in ``plans.search`` search for
the failing bit; here it follows from neighbours: of all allowed values, the next one above and the
next one below a value share the longest prefixes with it.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from keyhop.functions.bits import LIMB, LIMB_MASK, limbs, ones, runs, top_position
from keyhop.plans.search import Point, Restriction, Search

#: Up to so many intervals a decision tree of comparisons; beyond, a search in a literal array.
TREE = 256
#: A point's mask is cut in pieces of at most so many bits, so that its value fits a long.
PIECE = 48


def long(x: int) -> Column:
    return F.lit(x).cast("bigint")


def low_ones(bits: Column) -> Column:
    """A long with its ``bits`` (0 to 62) lowest bits set."""
    return F.call_function("shiftleft", long(1), bits.cast("int")) - long(1)


def _pieces(mask: int) -> list[tuple[int, int, int]]:
    """(limb counted from the junior end, shift in the limb, width) of a mask's runs, cut at limbs, senior first."""
    out = []
    for h, t in runs(mask):
        while h > t:
            limb = (h - 1) // LIMB
            low = max(t, limb * LIMB)
            out.append((limb, low - limb * LIMB, h - low))
            h = low
    return out


def gathered(keys: list[Column], mask: int) -> Column:
    """The masked bits of limb columns (senior first) as one number; at most 62 bits."""
    out = long(0)
    for limb, shift, width in _pieces(mask):
        piece = F.shiftright(keys[len(keys) - 1 - limb], shift).bitwiseAND(long(ones(width)))
        out = F.shiftleft(out, width).bitwiseOR(piece)
    return out


def scattered(value: Column, mask: int, count: int) -> list[Column]:
    """The inverse of :func:`gathered`: ``count`` limbs, senior first."""
    out = [long(0)] * count
    taken = 0
    for limb, shift, width in reversed(_pieces(mask)):
        piece = F.shiftleft(F.shiftright(value, taken).bitwiseAND(long(ones(width))), shift)
        out[count - 1 - limb] = out[count - 1 - limb].bitwiseOR(piece)
        taken += width
    return out


def _first(intervals: tuple[tuple[int, int], ...], v: Column, found: Callable[[int, int], Column]) -> Column:
    """``found`` of the first interval that ends at or above ``v``; null if there is none."""
    if len(intervals) > TREE:
        listed = F.array(*(F.struct(long(a).alias("a"), long(b).alias("b")) for a, b in intervals))
        at = F.get(F.filter(listed, lambda x: x["b"] >= v), 0)
        return found(at["a"], at["b"])
    if len(intervals) == 1:
        a, b = intervals[0]
        return F.when(v <= long(b), found(long(a), long(b)))
    middle = len(intervals) // 2
    return F.when(v <= long(intervals[middle - 1][1]), _first(intervals[:middle], v, found)).otherwise(_first(intervals[middle:], v, found))


def least_from(r: Restriction, v: Column) -> Column:
    """The smallest allowed value at or above ``v``, or null."""
    return _first(r.intervals, v, lambda a, b: F.greatest(v, a))


def end_from(r: Restriction, v: Column) -> Column:
    """The end of the first interval that reaches ``v``, or null."""
    return _first(r.intervals, v, lambda a, b: b)


def greatest_to(r: Restriction, v: Column) -> Column:
    """The greatest allowed value at or below ``v``, or null."""
    turned = tuple((-b, -a) for a, b in reversed(r.intervals))
    return -_first(turned, -v, lambda a, b: F.greatest(-v, a))


def places(mask: int) -> list[int]:
    """Key position (from 1) of each masked bit, junior first, after a 0 for no bit."""
    return [0, *(i + 1 for i in range(mask.bit_length()) if mask >> i & 1)]


def held_below(mask: int, n: int) -> list[int]:
    """For 0 to ``n``: the masked bits at or below that key position."""
    out = [0]
    for i in range(n):
        out.append(out[-1] + (mask >> i & 1))
    return out


def looked_up(values: list[int], at: Column) -> Column:
    return F.get(F.array(*map(F.lit, values)), at.cast("int"))


def split_points(search: Search) -> list[Restriction]:
    """The restrictions, each of few enough bits for a long."""
    out = []
    for r in search.restrictions:
        if r.width <= LIMB:
            out.append(r)
            continue
        if r.kind != "point":
            raise ValueError("a range or set of more bits than a limb")
        bits, value = [i for i in range(r.mask.bit_length()) if r.mask >> i & 1], r.intervals[0][0]
        for at in range(0, len(bits), PIECE):
            piece = bits[at : at + PIECE]
            out.append(Point(sum(1 << b for b in piece), value >> at & ones(len(piece))))
    return out


def after_eq(a: list[Column], b: list[Column]) -> Column:
    """Whether key ``a`` is at or above key ``b``, limb by limb."""
    out = a[-1] >= b[-1]
    for x, y in zip(reversed(a[:-1]), reversed(b[:-1]), strict=True):
        out = (x > y) | ((x == y) & out)
    return out


def within(keys: list[Column], lo: int, hi: int) -> Column:
    """Whether a key stands in [lo, hi]; the senior limb's bounds stand alone, for Parquet's statistics."""
    a, b = limbs(lo, len(keys)), limbs(hi, len(keys))
    out = keys[0].between(a[0], b[0])
    if len(keys) > 1:
        out = out & after_eq(keys, [long(x) for x in a]) & after_eq([long(x) for x in b], keys)
    return out


def settled(df: DataFrame, names: list[str]) -> DataFrame:
    """``df`` with its columns ``names`` computed here, once.

    Otherwise a filter on them would be pushed down through the projections that make them, spelling
    out each step's expressions in the next. They pass through a one-row generator, which stays in
    generated code and lets no such filter through; filters on the other columns go through.
    """
    own = [F.col(f"`{c}`") for c in df.columns if c not in names]
    return df.select(*own, F.explode(F.array(F.struct(*names))).alias("_settled")).select(*own, *(F.col(f"_settled.{c}").alias(c) for c in names))


def with_next_match(df: DataFrame, keys: list[str], search: Search, mismatch: str, following: list[str]) -> DataFrame:
    """``df`` with the signed mismatch and the limbs of the next match (null: none) of its key columns.

    Each step is a projection of its own, so that no expression is spelled out more than once. The
    search must not be empty.
    """
    rs, n, count = split_points(search), search.n, len(keys)
    own = list(df.columns)
    key = [F.col(k) for k in keys]
    col = lambda name, i: F.col(f"_{name}{i}")
    each = lambda name, make: {f"_{name}{i}": make(i, r) for i, r in enumerate(rs)}
    if not rs:
        return df.withColumns({mismatch: F.lit(0), **dict(zip(following, key, strict=True))})
    df = df.withColumns(each("v", lambda i, r: gathered(key, r.mask)))
    df = df.withColumns(each("up", lambda i, r: col("v", i).bitwiseXOR(least_from(r, col("v", i)))) | each("down", lambda i, r: col("v", i).bitwiseXOR(greatest_to(r, col("v", i)))))
    df = df.withColumns(each("pos", lambda i, r: looked_up(places(r.mask), top_position(F.least(col("up", i), col("down", i))))))
    furthest = F.greatest(*(col("pos", i) for i in range(len(rs))), F.lit(0))
    df = df.withColumn("_far", furthest)
    below = F.coalesce(*(F.when(col("pos", i) == F.col("_far"), col("up", i).isNotNull() & (col("down", i).isNull() | (col("up", i) < col("down", i)))) for i in range(len(rs))))
    df = df.withColumn("_below", below)
    # Above the failing bit: the lowest zero bit that no mask holds, or that leads a masked value to a larger allowed one.
    free = ones(n) & ~search.mask
    open_bits = []
    for limb in range(count):
        under = F.least(F.greatest(F.col("_far") - limb * LIMB, F.lit(0)), F.lit(LIMB))
        zeros = F.bitwise_not(key[count - 1 - limb]).bitwiseAND(long(free >> (limb * LIMB) & LIMB_MASK)).bitwiseAND(F.bitwise_not(low_ones(under)))
        open_bits.append(F.when(zeros != 0, top_position(zeros.bitwiseAND(-zeros)) + limb * LIMB))
    df = df.withColumns({"_open": F.coalesce(*open_bits)} | each("w", lambda i, r: col("v", i).bitwiseOR(low_ones(looked_up(held_below(r.mask, n), F.col("_far")))) + long(1)))
    df = df.withColumns(each("up2", lambda i, r: col("v", i).bitwiseXOR(least_from(r, col("w", i)))))
    grown = F.least(F.col("_open"), *(F.when(col("up2", i).isNotNull(), looked_up(places(r.mask), top_position(col("up2", i)))) for i, r in enumerate(rs)), F.lit(n + 1))
    df = df.withColumn("_bit", F.when(F.col("_below"), F.col("_far")).otherwise(F.when(grown <= n, grown)))
    raised = {}
    for limb in range(count):
        at = F.col("_bit") - limb * LIMB
        here = F.least(F.greatest(at - 1, F.lit(0)), F.lit(LIMB))
        k = key[count - 1 - limb]
        set_here = F.call_function("shiftleft", long(1), F.greatest(F.least(at - 1, F.lit(LIMB - 1)), F.lit(0)).cast("int"))
        raised[f"_raised{limb}"] = F.when(at <= 0, k).when(at > LIMB, long(0)).otherwise(k.bitwiseOR(set_here).bitwiseAND(F.bitwise_not(low_ones(here))))
    df = df.withColumns(raised)
    up = [F.col(f"_raised{count - 1 - j}") for j in range(count)]
    df = df.withColumns(each("base", lambda i, r: gathered(up, r.mask)))
    df = df.withColumns(each("least", lambda i, r: least_from(r, col("base", i))))
    completed = [u.bitwiseAND(long(LIMB_MASK & ~m)) for u, m in zip(up, limbs(search.mask, count), strict=True)]
    for i, r in enumerate(rs):
        completed = [c.bitwiseOR(s) for c, s in zip(completed, scattered(col("least", i), r.mask, count), strict=True)]
    matched = F.col("_far") == 0
    signed = F.when(matched, F.lit(0)).when(F.col("_below"), -F.col("_far")).otherwise(F.col("_far"))
    out = {mismatch: signed.cast("int")} | {h: F.when(matched, k).when(F.col("_bit").isNotNull(), c) for h, k, c in zip(following, key, completed, strict=True)}
    return settled(df.withColumns(out).select(*(F.col(f"`{c}`") for c in own), mismatch, *following), [mismatch, *following])


def match(keys: list[Column], search: Search) -> Column:
    """Whether a key matches."""
    if search.empty:
        return F.lit(False)
    out = F.lit(True)
    for r in split_points(search):
        v = gathered(keys, r.mask)
        out = out & F.coalesce(least_from(r, v) == v, F.lit(False))
    return out


def width_of(lo: list[Column], hi: list[Column]) -> Column:
    """Number of junior bits in which two keys differ."""
    count = len(lo)
    return F.coalesce(*(F.when(a != b, top_position(a.bitwiseXOR(b)) + (count - 1 - j) * LIMB) for j, (a, b) in enumerate(zip(lo, hi, strict=True))), F.lit(0))


def whole(lo: list[Column], width: Column, search: Search) -> Column:
    """Whether all keys match that share all but the ``width`` junior bits with ``lo``."""
    out = F.lit(True)
    for r in split_points(search):
        v, low = gathered(lo, r.mask), low_ones(looked_up(held_below(r.mask, search.n), width))
        first, last = v.bitwiseAND(F.bitwise_not(low)), v.bitwiseOR(low)
        out = out & F.coalesce((least_from(r, first) == first) & (end_from(r, first) >= last), F.lit(False))
    return out


def threshold(rows: Column, width: Column, search: Search, ratio: float) -> Column:
    """The threshold for ``rows`` rows whose keys differ in ``width`` junior bits.

    The lower of the one from the number of rows and the one from the gaps of the mask's runs within
    these bits; 0 for a point search where jumping always is proven to win.
    """
    useful = F.log2(F.greatest(rows * ratio, F.lit(1.0)))
    tails = sorted({t for r in search.restrictions for _, t in runs(r.mask)})
    least_tail = F.least(F.lit(tails[0]), width)
    by_rows = F.least(F.greatest(F.ceil(width - useful).cast("int"), F.lit(0), least_tail), width)
    limit = F.pow(F.lit(2.0), width.cast("double")) / F.greatest(rows * ratio, F.lit(1e-9))
    size = lambda h, t: F.when(width > t, F.pow(F.lit(2.0), F.least(F.lit(h), width).cast("double")) - F.lit(2.0**t)).otherwise(F.lit(0.0))
    by_gaps = width
    for t in reversed(tails):
        terms = [size(h, u) for r in search.restrictions for h, u in runs(r.mask) if u <= t]
        by_gaps = F.when((width > t) & (sum(terms[1:], terms[0]) > limit), F.lit(t)).otherwise(by_gaps)
    best = F.least(by_rows, by_gaps)
    if search.point:
        d = looked_up(held_below(search.mask, search.n), width).cast("double")
        gaps = F.pow(F.lit(2.0), F.greatest(width - d - least_tail, F.lit(0.0))) - 1
        wins = (d > 0) & (gaps < ratio * rows * (1 - F.pow(F.lit(2.0), -d)))
        best = F.when(wins, F.lit(0)).otherwise(best)
    return best.cast("int")
