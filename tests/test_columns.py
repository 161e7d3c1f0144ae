import random

import pytest
from pyspark.sql import functions as F

from keyhop.functions.bits import joined, limbs, ones
from keyhop.plans import columns
from keyhop.plans.restrict import normalize, reduce_for_interval
from keyhop.plans.search import InSet, Point, Range, Restriction, Search, normal_intervals


def drawn(rng, n, most):
    """A search with up to three restrictions of any kind on random bits."""
    bits = list(range(n))
    rng.shuffle(bits)
    out = []
    for _ in range(rng.randint(1, 3)):
        width = rng.randint(1, most)
        taken, bits = bits[:width], bits[width:]
        if len(taken) < width:
            break
        mask, size = sum(1 << b for b in taken), 1 << width
        kind = rng.choice("PRSU")
        if kind == "P":
            out.append(Point(mask, rng.randrange(size)))
        elif kind == "R":
            out.append(Range(mask, *sorted((rng.randrange(size), rng.randrange(size)))))
        elif kind == "S":
            out.append(InSet(mask, [rng.randrange(size) for _ in range(rng.randint(1, 9))]))
        else:
            ends = sorted(rng.randrange(size) for _ in range(2 * rng.randint(1, 4)))
            out.append(Restriction(mask, normal_intervals(zip(ends[::2], ends[1::2], strict=True))))
    return Search(n, tuple(out))


@pytest.mark.parametrize(("n", "most", "searches"), [(7, 3, 10), (62, 12, 4), (70, 20, 4), (130, 30, 4)])
def test_next_match_of_columns_equals_the_scalar_one(spark, n, most, searches):
    rng = random.Random(n)
    for _ in range(searches):
        search = drawn(rng, n, most)
        search = search if rng.random() < 0.5 else normalize(search)
        count = max(1, -(-n // 62))
        keys = range(1 << n) if n < 8 else [rng.getrandbits(n) for _ in range(150)]
        if n > 8:  # keys near matches
            keys += [max(0, min(ones(n), k + d)) for k in [search.next_match(k) for k in keys[:60]] if k is not None for d in (-1, 0, 1)]
            keys += [(search.next_match(k) or 0) ^ (1 << rng.randrange(n)) for k in keys[:60]]
        names = [f"k{i}" for i in range(count)]
        df = spark.createDataFrame([tuple(limbs(k, count)) for k in keys], ", ".join(f"{x} bigint" for x in names))
        following = [f"h{i}" for i in range(count)]
        got = columns.with_next_match(df, names, search, "y", following).withColumn("m", columns.match([F.col(x) for x in names], search))
        assert "Python" not in got._jdf.queryExecution().toString()
        for r in got.collect():
            key = joined([r[x] for x in names])
            want = search.next_match(key)
            assert r["y"] == search.mismatch(key) and r["m"] == search.match(key)
            assert want == (None if r["h0"] is None else joined([r[x] for x in following]))


@pytest.mark.parametrize(("n", "most"), [(9, 3), (70, 20)])
def test_whole_slices_of_columns(spark, n, most):
    rng = random.Random(n)
    count = max(1, -(-n // 62))
    for _ in range(5):
        search = drawn(rng, n, most)
        rows = []
        for _ in range(200):
            width, key = rng.randint(0, n), rng.getrandbits(n)
            key = key if rng.random() < 0.5 else search.next_match(key) or key
            ends = sorted((key & ~ones(width) | rng.getrandbits(width), key & ~ones(width) | rng.getrandbits(width))) if width else (key, key)
            rows.append((*limbs(ends[0], count), *limbs(ends[1], count)))
        names = [f"{s}{i}" for s in ("lo", "hi") for i in range(count)]
        lo, hi = ([F.col(f"{s}{i}") for i in range(count)] for s in ("lo", "hi"))
        df = spark.createDataFrame(rows, ", ".join(f"{x} bigint" for x in names)).withColumn("width", columns.width_of(lo, hi))
        for r in df.withColumn("whole", columns.whole(lo, F.col("width"), search)).withColumn("t", columns.threshold(F.lit(100), F.col("width"), search, 0.5)).collect():
            a, b = joined([r[f"lo{i}"] for i in range(count)]), joined([r[f"hi{i}"] for i in range(count)])
            assert r["width"] == (a ^ b).bit_length() and 0 <= r["t"] <= max(r["width"], 0)
            reduced = reduce_for_interval(search, a, b)
            assert r["whole"] == (reduced is not None and not reduced.restrictions)
