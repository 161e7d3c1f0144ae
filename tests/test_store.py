import datetime as dt
import math
import random
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from keyhop import queries as engine
from keyhop import workload as wl
from keyhop.calibrate import calibrate
from keyhop.functions.bits import gather, joined
from keyhop.functions.curve import Attribute, Codec, KeyLayout
from keyhop.functions.dictionary import build_dictionary
from keyhop.operators import race
from keyhop.operators.race import Cursor, PatternTotals, PointRun, average_counters, cursor_counters, declarative_counters, point_counters, points_counters, walk
from keyhop.plans import costs, geometry
from keyhop.plans.filters import AnyOf, Between, Eq, In, IsNull, NotIn, NotNull, Prefix, condition
from keyhop.plans.search import Point, Search, next_match_udf
from keyhop.sources.facts import FACTS, fact
from keyhop.sources import store as store_module
from keyhop.sources.store import KeyedStore

FILTERS = [
    {"l_quantity": Eq(17.0)},
    {"l_shipdate": Between(dt.date(1996, 1, 1), dt.date(1996, 12, 31)), "l_suppkey": In((3, 5, 9))},
    {"l_quantity": AnyOf((Eq(2.0), Between(20.0, 25.0))), "l_partkey": Between(10, 90)},
    {"l_quantity": NotIn((1.0, 2.0)), "l_discount": Eq(0.05)},
    {"l_quantity": Eq(1000.0)},
    {"l_partkey": Between(None, None)},
]


@pytest.fixture(scope="module")
def five(spark, sf):
    return wl.store(spark, sf, "fact5")


def keys_of(store):
    return sorted(joined(list(r)) for r in store.data.select(*store.layout.key_columns).collect())


@pytest.mark.parametrize("name", ["fact5", "fact16"])
@pytest.mark.parametrize("aligned", [False, True])
def test_counts_equal_a_scan(spark, sf, name, aligned):
    store = wl.store(spark, sf, name, aligned=aligned)
    rows = fact(spark, sf, name)
    for filters in FILTERS:
        if "l_discount" in filters and name == "fact16":
            continue
        want = rows.where(condition(store.layout, filters)).count()
        assert store.count_where(**filters).first()[0] == want
        assert store.where(**filters).count() == want


def test_strategies_take_the_same_rows_and_both_executors_agree(five):
    keys, n = keys_of(five), five.layout.n
    for filters in FILTERS:
        search = five.search(**filters)
        declared = {r["threshold"]: r for r in declarative_counters(five.data, five.layout.key_columns, search, [0, 9, n // 2, n]).collect()}
        taken = walk(keys, search, n)[0]
        for t, r in declared.items():
            got, c = walk(keys, search, t)
            assert got == taken and (c.matched, c.scans, c.jumps) == (r["matched"], r["scans"], r["jumps"])
            assert walk(keys, search, t, cluster_end=True)[0] == taken
            assert walk(keys, search, t, max(0, t - 3))[0] == taken
        if search.point:
            assert {tuple(r) for r in point_counters(five.data, search, [0, 9, n]).select("threshold", "matched", "scans", "jumps").collect()} == {tuple(declared[t]) for t in (0, 9)} | {tuple(declared[n])}
        sliced = cursor_counters(five, search, n // 2).agg(F.sum("matched")).first()[0]
        assert sliced == len(taken)


@pytest.mark.parametrize("listed", [4096, 3])
@pytest.mark.parametrize("filters", FILTERS[:4])
def test_counts_by_strategy_with_listed_and_joined_catalogs(spark, sf, monkeypatch, listed, filters):
    """A catalog above the listed size is decided on by column expressions and joined; answers are the same."""
    monkeypatch.setattr(store_module, "LISTED_SLICES", listed)
    store = KeyedStore.open(spark, wl.store(spark, sf, "fact5").path)
    assert (store.listed() is None) == (listed == 3)
    rows = fact(spark, sf, "fact5").where(condition(store.layout, filters))
    want = rows.count()
    for strategy in ("crawl", "leap", "hybrid"):
        df = store.count_where(strategy, 1e-3, **filters)
        assert "Python" not in df._jdf.queryExecution().toString()
        assert df.first()[0] == want
    assert [r["k0"] for r in store.first(5, **filters).collect()] == [r["k0"] for r in store.layout.encode(rows).orderBy("k0").limit(5).collect()]


def test_decisions_equal_the_classified_catalog(five):
    for filters in FILTERS:
        search = five.search(**filters)
        actions = {r["slice"]: r["action"] for r in five.classify(search).where("action <> 'skip'").collect()}
        assert actions == {n: a for n, _, a in five.decisions(search)}
        crawled, hybrid = ({n for n, _, _ in five.decisions(search, x, 1e-9)} for x in ("crawl", "hybrid"))
        assert set(actions) <= hybrid <= crawled or not crawled


def test_cursor_over_batches_walks_as_the_scalar_one(five):
    import numpy as np

    keys = keys_of(five)
    for filters in FILTERS[:4]:
        search = five.search(**filters)
        lo, hi = search.bounds()
        inside = [k for k in keys if lo <= k <= hi]
        y = np.array([search.mismatch(k) for k in inside])
        h = np.array([search.next_match(k) for k in inside])
        low = search.mask & -search.mask
        for t, above in ((0, None), (9, None), (20, 12), (five.layout.n, None)):
            cursor = Cursor(t, above, True)
            for part in np.array_split(np.arange(len(inside)), 7):
                k = np.array(inside, np.int64)[part]
                cursor.walk([k], y[part], [h[part]], [k // low])
            _, c = walk(keys, search, t, above)
            assert (cursor.matched, cursor.scans, cursor.jumps) == (c.matched, c.scans, c.jumps)
            assert cursor.scans + cursor.jumps <= cursor.tests <= cursor.scans + cursor.jumps + cursor.matched


def test_totals_over_patterns_of_any_batches_and_tasks():
    """Random keys, masks and thresholds, dealt to tasks and batches at random."""
    names = ("first", "last", "leap", "hybrid", "crawl", "scans", "open", "before")
    for seed in range(300):
        rng = random.Random(seed)
        n = rng.randint(2, 8)
        mask, t, rows = rng.randint(1, (1 << n) - 1), rng.randint(0, n), Counter(rng.choices(range(1 << n), k=rng.randint(0, 25)))
        want = Counter(leap_jumps=0, crawl_scans=0, hybrid_jumps=0, hybrid_scans=0)
        for p in range(1 << mask.bit_count()):
            leap, crawl, hybrid = (walk(sorted(rows.elements()), Search(n, (Point(mask, p),)), x)[1] for x in (0, n, t))
            want.update(leap_jumps=leap.jumps, crawl_scans=crawl.scans, hybrid_jumps=hybrid.jumps, hybrid_scans=hybrid.scans)
        tasks, keys = [], sorted(rows)
        while keys:
            task = PatternTotals(mask, n, t)
            for _ in range(rng.randint(1, 3)):
                part, keys = keys[: (size := rng.randint(0, 5))], keys[size:]
                task.add(np.array(part, np.int64), np.array([rows[k] for k in part], np.int64))
            tasks += [{c: getattr(task, c) for c in names}] if task.first is not None else []
        assert PatternTotals.joined(tasks, mask, n, t) == dict(want)


def test_average_over_more_patterns_than_could_be_listed(spark):
    """Forty masked bits: the only row lies in the gap of every pattern but that of zeros."""
    one, rest = spark.createDataFrame([(1 << 61,)], "k0 bigint"), 2**40 - 1
    for t, jumps in ((0, rest), (41, 0)):
        assert average_counters(one, rest, 62, t).first().asDict() == {"leap_jumps": rest, "crawl_scans": rest, "hybrid_jumps": jumps, "hybrid_scans": rest - jumps}


def test_point_counters_of_any_batches_and_tasks():
    """Random keys and points, dealt to runs and batches at random; long keys near powers of two among them."""
    for seed in range(600):
        rng = random.Random(seed)
        n = rng.randint(2, 8) if seed % 2 else 60
        mask, t, base = rng.randint(1, (1 << n) - 1), rng.randint(0, n), rng.randrange(1 << n)
        keys = sorted(rng.choice([rng.randrange(1 << n), base, base ^ rng.randrange(4), (1 << n) - 1 - rng.randrange(4), rng.randrange(4)]) for _ in range(rng.randint(0, 25)))
        pattern = rng.choice([*keys, 0, (1 << n) - 1]) & mask
        want = walk(keys, Search(n, (Point(mask, gather(pattern, mask)),)), t)[1]
        runs = []
        while keys:
            run = PointRun(0, mask, pattern, n, t)
            for _ in range(rng.randint(1, 3)):
                part, keys = keys[: (size := rng.randint(0, 5))], keys[size:]
                run.add(np.array(part, np.int64), {})
            runs += [dict(zip(PointRun.COLUMNS, run.row(), strict=True))] if run.begin is not None else []
        assert PointRun.joined(runs) == (want.matched, want.scans, want.jumps)


def test_points_are_counted_in_one_pass_in_any_order_and_by_keys_alone(spark, sf, five):
    keys, n = keys_of(five), five.layout.n
    bare = wl.store(spark, sf, "fact5", keys_only=True)
    assert bare.attributes == [] and keys_of(bare) == keys
    searches = {a: (five.search(**f), [0, 7, 20, n]) for a, f in {"q": {"l_quantity": Eq(17.0)}, "p": {"l_partkey": Eq(7)}, "two": {"l_suppkey": Eq(3), "l_discount": Eq(0.05)}}.items()}
    want = {a: {t: (c.matched, c.scans, c.jumps) for t in ts for c in [walk(keys, search, t)[1]]} for a, (search, ts) in searches.items()}
    mingled = five.data.withColumn("slice", F.pmod("k0", F.lit(3)))  # slices that overlap
    for rows in (five.data, bare.data, mingled, five.data.drop("slice").repartition(5)):
        assert points_counters(rows, searches) == want


def test_regions_are_pushed_to_the_scan(spark, sf, five):
    five = wl.store(spark, sf, "fact5", slices=4, row_group_rows=500)
    spark.conf.set("spark.sql.maxMetadataStringLength", "5000")
    plan = five.where(["l_suppkey"], "leap", l_quantity=Eq(17.0), l_discount=Eq(0.05))._jdf.queryExecution().toString()
    pushed = plan[plan.index("PushedFilters: [") :]
    assert "Or(" in pushed and "l_discount" in pushed and "k0" in pushed
    dated = five.where(["l_suppkey"], l_shipdate=Between(dt.date(1996, 1, 1), dt.date(1996, 2, 1)))._jdf.queryExecution().toString()
    spark.conf.unset("spark.sql.maxMetadataStringLength")
    assert "GreaterThanOrEqual(l_shipdate" in dated


def test_average_over_patterns(five):
    keys, n, mask = keys_of(five), five.layout.n, five.layout.mask("l_discount")
    t = costs.threshold_cardinality(n, len(keys), 0.5, mask)
    total = Counter()
    for p in range(1 << mask.bit_count()):
        search = Search(n, (Point(mask, p),))
        leap, crawl, hybrid = (walk(keys, search, x)[1] for x in (0, n, t))
        total.update(leap_jumps=leap.jumps, crawl_scans=crawl.scans, hybrid_jumps=hybrid.jumps, hybrid_scans=hybrid.scans)
    assert average_counters(five.data, mask, n, t).first().asDict() == dict(total)
    assert total["leap_jumps"] <= costs.jump_bound(mask, n)


def test_average_cost_of_every_attribute_and_pair(spark, sf, five):
    keys, n, layout = keys_of(five), five.layout.n, five.layout
    got = {r["attribute"]: r for r in engine.queries()["avg_cost_per_mask"](spark, sf).collect()}
    names = FACTS["fact5"]
    assert set(got) == {*names, *(f"{a},{b}" for i, a in enumerate(names) for b in names[i + 1 :])}
    for r in got.values():
        masked = [layout.mask(a) for a in r["attribute"].split(",")]
        assert r["d"] == sum(m.bit_count() for m in masked) and r["bound_holds"]
        assert int(r["crawl_total"]) == (2 ** r["d"] - 1) * len(keys)
        assert math.isclose(r["r2"], int(r["crawl_scans"]) / int(r["crawl_total"]), rel_tol=1e-12)  # two ways to count the patterns in whose gaps a row lies
        assert r["sigma"] == costs.region_sigma(five.data, sum(masked), n)
    mask = layout.mask("l_suppkey") | layout.mask("l_discount")
    t, total = costs.threshold_cardinality(n, len(keys), 0.5, mask), Counter()
    for p in range(1 << mask.bit_count()):
        leap, crawl, hybrid = (walk(keys, Search(n, (Point(mask, p),)), x)[1] for x in (0, n, t))
        total.update(leap_jumps=leap.jumps, crawl_scans=crawl.scans, hybrid_jumps=hybrid.jumps, hybrid_scans=hybrid.scans)
    assert {c: got["l_suppkey,l_discount"][c] for c in total} == dict(total)


def test_region_sigmas_in_one_pass(spark, five):
    n, masks = five.layout.n, [five.layout.mask(a) for a in FACTS["fact5"]] + [1 << five.layout.n - 1, 1 << five.layout.n - 3]
    skewed = five.data.union(five.data.where("l_suppkey <= 2"))  # the same keys in two runs
    mingled = five.data.withColumn("slice", F.pmod(F.xxhash64("l_extendedprice"), F.lit(3)))  # slices that overlap
    for rows in (five.data, skewed, mingled, five.data.drop("slice").repartition(5), five.data.where("false")):
        assert race.region_sigmas(rows, masks, n) == {m: costs.region_sigma(rows, m, n) for m in masks}


def test_region_runs_of_any_batches_and_tasks():
    for seed in range(300):
        rng = random.Random(seed)
        n = rng.randint(1, 8)
        t, keys = rng.randint(0, n), sorted(rng.choices(range(1 << n), k=rng.randint(0, 60)))
        want, runs, rows = sum(m * m for m in Counter(k >> t for k in keys).values()), [], len(keys)
        while keys:
            run = race.RegionRun(t)
            for _ in range(rng.randint(1, 3)):
                part, keys = keys[: (size := rng.randint(0, 9))], keys[size:]
                run.add(np.array(part, np.int64), {})
            runs += [dict(zip(race.RegionRun.COLUMNS, run.row(), strict=True))] if run.begin is not None else []
        assert race.RegionRun.joined(runs) == (rows, want)


def test_cofrequency_columns_of_many_masks(spark):
    rng, n = random.Random(5), 61
    masks, keys = [rng.randrange(1, 1 << n) & rng.randrange(1 << n) for _ in range(15)], [rng.randrange(1 << n) >> rng.randrange(n) for _ in range(40)] + [0, (1 << n) - 1]
    rows = spark.createDataFrame([(k,) for k in keys], "k0 bigint")
    for r in rows.select("k0", *(costs.cofrequency_column(F.col("k0"), m, n).alias(str(m)) for m in masks)).collect():
        assert [r[str(m)] for m in masks] == [geometry.cofrequency(r["k0"], m, n) for m in masks]
    means = {m: sum(geometry.cofrequency(k, m, n) for k in keys) / len(keys) / (2 ** m.bit_count() - 1) for m in masks}
    assert costs.r2s(rows, masks, n) == pytest.approx(means, rel=1e-12)


def test_average_of_totals_beyond_a_long(spark):
    """A thousand rows with the same key, which lies in the gaps of 2^61 - 1 patterns."""
    rows, each = spark.range(1000).select(F.lit(1 << 61).alias("k0")), 2**61 - 1
    assert average_counters(rows, each, 62, 62).first().asDict() == {"leap_jumps": each, "crawl_scans": 1000 * each, "hybrid_jumps": 0, "hybrid_scans": 1000 * each}
    assert race.total(np.array([each, 3, 2**62]), np.array([1 << 33, 5, 1])) == (each << 33) + 15 + 2**62
    with pytest.raises(ValueError, match="one limb"):
        average_counters(rows, 1, 63, 0)


def test_column_forms(five):
    search = five.search(l_quantity=Eq(9.0), l_discount=Eq(0.03))
    from keyhop.runtime import ship

    ship(five.spark)
    both = five.data.select(search.next_match_column(F.col("k0")).alias("a"), F.get(next_match_udf(search, 1)(F.array("k0")), 0).alias("b"), search.match_column(F.col("k0")).alias("m"), "k0")
    for r in both.collect():
        assert r["a"] == r["b"] == search.next_match(r["k0"]) and r["m"] == search.match(r["k0"])


@pytest.mark.parametrize("kind", ["interleave", "junior", "odometer", "blocked2", "blocked4", "last:l_discount"])
def test_layouts_are_monotone_bijections(spark, sf, kind):
    df = fact(spark, sf, "fact5")
    layout = wl.layout_of(df, "fact5", kind)
    assert sorted(p for places in layout.place.values() for p in places) == list(range(layout.n))
    assert all(list(p) == sorted(p) for p in layout.place.values())
    wrong = [layout.code_expression(a.name) != a.codec.column(F.col(a.name)) for a in layout.attributes]
    assert layout.encode(df).where(wrong[0] | wrong[1] | wrong[2] | wrong[3] | wrong[4]).count() == 0


def test_wide_keys(spark, sf):
    df = fact(spark, sf, "fact18")
    layout = wl.layout_of(df, "fact18", "interleave")
    assert layout.limb_count == 2
    coded = layout.encode(df)
    for a in layout.attributes[:3]:
        assert coded.where(layout.code_expression(a.name) != a.codec.column(F.col(a.name))).count() == 0


def test_nulls_bins_and_strings(spark, sf):
    store = wl.store(spark, sf, "doc5")
    rows = fact(spark, sf, "doc5")
    for filters in ({"quality": IsNull()}, {"quality": NotNull()}, {"n_chars": Between(300, 1200)}, {"lang": Prefix("e"), "quality": Eq(1)}):
        assert store.count_where(**filters).first()[0] == rows.where(condition(None, filters)).count()


def test_opened_compacted_and_sql(spark, sf, five):
    again = KeyedStore.open(spark, five.path)
    assert again.layout.to_json() == five.layout.to_json() and again.rows == five.rows
    info = five.explain(l_quantity=Eq(5.0))
    assert sum(n for n, _ in info["slices"].values()) == five.catalog.count() and info["slices"]["skip"][0] > 0
    first = five.first(10, l_quantity=Eq(17.0)).select("k0").collect()
    matching = five.data.where("l_quantity = 17").orderBy("k0").limit(10).select("k0").collect()
    assert first == matching


def test_plan_prunes_and_stays_in_the_jvm(five):
    plan = five.where(["l_suppkey"], l_quantity=Eq(17.0))._jdf.queryExecution().toString()
    assert "PartitionFilters" in plan and "PushedFilters: [" in plan and "Python" not in plan and "Arrow" not in plan


def test_dictionary(spark, sf):
    rows = build_dictionary(spark.read.parquet(f"{sf}/part.parquet"), "p_brand").orderBy("code").collect()
    assert [r["code"] for r in rows] == list(range(1, len(rows) + 1)) and [r["value"] for r in rows] == sorted(r["value"] for r in rows)


def test_whole_slices_are_counted_from_the_catalog(spark, sf):
    store = wl.store(spark, sf, "fact5", layout="odometer", aligned=True)
    search = store.search(l_partkey=Between(0, 120))
    actions = {r["action"]: r["slices"] for r in store.io_report(search).collect()}
    assert actions.get("whole", 0) > 0
    assert store.count_where(l_partkey=Between(0, 120)).first()[0] == fact(spark, sf, "fact5").where("l_partkey <= 120").count()
    assert set(FACTS["fact5"]) == {a.name for a in store.layout.attributes}


def test_calibration_reads_keys_whose_sum_is_no_long(spark, tmp_path):
    """Ten keys of 61 bits: their sum doesn't fit into 64."""
    size = 1 << 60
    rows = spark.range(10).select((F.lit(size - 1) - F.col("id")).alias("x"))
    store = KeyedStore.build(rows, KeyLayout.odometer([Attribute("x", Codec("raw", 0, size=size))]), str(tmp_path / "long"), 2)
    assert sum(keys_of(store)) > 1 << 63
    assert all(v > 0 for v in calibrate(store).values())
