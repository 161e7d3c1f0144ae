"""The engine's queries, each with its SQL where SQL can express it."""

from __future__ import annotations

import datetime as dt
import itertools
from collections.abc import Callable
from decimal import Decimal

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from keyhop.functions.dictionary import build_dictionary
from keyhop.operators.race import averages, crawl_counters, cursor_counters, declarative_counters, leap_counters, point_counters, points_counters, race, region_sigmas
from keyhop.operators.surround import all_operators
from keyhop.plans import costs, geometry
from keyhop.plans.columns import with_next_match
from keyhop.plans.filters import AnyOf, Between, Eq, Filter, In, IsNull, NotIn, Prefix, condition
from keyhop.runtime import Scratch, table
from keyhop.sources.facts import FACTS, STAR_SQL, events, fact
from keyhop.sources.store import KeyedStore
from keyhop.streaming.store import event_stream, finished, stream_store
from keyhop import oracles
from keyhop import workload as wl

Query = Callable[[SparkSession, str], DataFrame]
_Q: dict[str, Query] = {}
_SQL: dict[str, str] = {}
#: Scan-to-seek ratio in queries that need one, so that results repeat.
RATIO = 0.5


def _add(name: str, query: Query, sql: str | None = None) -> None:
    _Q[name] = query
    if sql:
        _SQL[name] = sql


def _rows(spark: SparkSession, rows: list, schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def _count(w: wl.Workload) -> Query:
    return lambda spark, sf: wl.store(spark, sf, w.fact).count_where(**w.filters)


def _counts() -> None:
    """Every attribute by point, range and set; mixes of kinds on up to three attributes; multiple points."""
    for kind in "PRS":
        for w in wl.single("fact16", kind):
            _add(f"count_{w.name}", _count(w), w.sql)
    for kinds in ("PP", "PR", "PS", "RR", "RS", "SS", "PPP", "PPR", "PPS", "PRR", "PRS", "PSS", "RRR", "RRS", "RSS", "SSS"):
        for w in wl.mixes("fact16", kinds, 2):
            _add(f"count_{w.name}", _count(w), w.sql)
    for name in ("fact10", "fact5"):
        for w in wl.points(name, 5, 2):
            _add(f"count_{name}_{w.name}", _count(w), w.sql)


def _contest() -> None:
    for i, w in enumerate(wl.contest()):
        if i % 2:

            def run(spark: SparkSession, sf: str, w: wl.Workload = w) -> DataFrame:
                return wl.store(spark, sf, w.fact).where(["l_extendedprice"], **w.filters).agg(F.count(F.lit(1)).alias("count"), F.sum(F.col("l_extendedprice").cast("decimal(15,2)")).cast("double").alias("total"))

            _add(f"contest_{w.name}", run, f"SELECT count(*) AS count, CAST(sum(CAST(l_extendedprice AS DECIMAL(15,2))) AS DOUBLE) AS total FROM ({STAR_SQL}) f WHERE {wl.where_sql(w.filters)}")
        else:
            _add(f"contest_{w.name}", _count(w), w.sql)


MIXED: dict[str, dict[str, Filter]] = {
    "point": {"l_quantity": Eq(17.0)},
    "range": {"l_shipdate": Between(dt.date(1996, 1, 1), dt.date(1996, 12, 31))},
    "set": {"l_suppkey": In((2, 3, 5, 7))},
    "mixed": {"l_quantity": Eq(5.0), "l_shipdate": Between(dt.date(1996, 1, 1), dt.date(1998, 6, 30)), "l_discount": In((0.01, 0.04, 0.09))},
}


def _rows_threshold(s: KeyedStore, filters: dict[str, Filter]) -> int:
    """The threshold from the number of rows, for the masks of the restricted attributes."""
    mask = 0
    for a in filters:
        mask |= s.layout.mask(a)
    return costs.threshold_cardinality(s.layout.n, s.rows, RATIO, mask)


def crawl(spark: SparkSession, sf: str, filters: dict[str, Filter]) -> DataFrame:
    s = wl.store(spark, sf, "fact5")
    return crawl_counters(s.data, s.layout.key_columns, s.search(**filters))


def leap(spark: SparkSession, sf: str, filters: dict[str, Filter]) -> DataFrame:
    s = wl.store(spark, sf, "fact5")
    return leap_counters(s.data, s.layout.key_columns, s.search(**filters))


def hybrid(spark: SparkSession, sf: str, filters: dict[str, Filter]) -> DataFrame:
    s = wl.store(spark, sf, "fact5")
    return declarative_counters(s.data, s.layout.key_columns, s.search(**filters), [_rows_threshold(s, filters)]).drop("threshold")


def walked(spark: SparkSession, sf: str, filters: dict[str, Filter], two: bool = False, cluster_end: bool = False) -> DataFrame:
    s = wl.store(spark, sf, "fact5")
    search = s.search(**filters)
    t = costs.choose_threshold(search, s.rows, RATIO).threshold
    return cursor_counters(s, search, t, max(0, t - 2) if two else None, cluster_end).agg(F.coalesce(F.sum("matched"), F.lit(0)).alias("matched"))


def counters(spark: SparkSession, sf: str, filters: dict[str, Filter]) -> DataFrame:
    """Counters and cost of the three strategies, hybrid at the threshold from the number of rows."""
    s = wl.store(spark, sf, "fact5")
    return race(s, s.search(**filters), RATIO, {"crawl": s.layout.n, "leap": 0, "hybrid": _rows_threshold(s, filters)})


def _strategies() -> None:
    """The same rows by every strategy and executor, and what each does for them."""
    cost = f"CAST(scans * {RATIO} + jumps AS DOUBLE) AS cost"
    for kind, filters in MIXED.items():
        bind = lambda f, filters=filters, **options: lambda spark, sf: f(spark, sf, filters, **options)
        sql = f"SELECT count(*) AS matched FROM lineitem WHERE {wl.where_sql(filters)}"
        by_rows = oracles.rows_threshold_sql(RATIO)
        _add(f"crawl_{kind}", bind(crawl), oracles.crawl_sql(filters))
        _add(f"leap_{kind}", bind(leap), oracles.leap_sql(filters))
        _add(f"hybrid_{kind}", bind(hybrid), oracles.counters_sql(filters, f"SELECT {by_rows} AS t FROM total") + " SELECT matched, scans, jumps FROM counted")
        _add(f"hybrid_cursor_{kind}", bind(walked), sql)
        _add(f"hybrid_two_thresholds_{kind}", bind(walked, two=True), sql)
        _add(f"hybrid_cluster_end_{kind}", bind(walked, cluster_end=True), sql)
        _add(f"hybrid_sliced_{kind}", lambda spark, sf, filters=filters: wl.store(spark, sf, "fact5").where([], **filters).agg(F.count(F.lit(1)).alias("matched")), sql)
        named = f"SELECT 'crawl' AS strategy, n AS t FROM total UNION ALL SELECT 'leap', 0 UNION ALL SELECT 'hybrid', {by_rows} FROM total"
        each = oracles.counters_sql(filters, f"SELECT DISTINCT t FROM ({named})")
        _add(f"counters_{kind}", bind(counters), f"{each} SELECT strategy, threshold, matched, scans, jumps, {cost} FROM counted JOIN ({named}) s ON s.t = counted.threshold")
        _add(f"race_{kind}", bind(_race))
        _add(f"threshold_sweep_{kind}", bind(_sweep), oracles.counters_sql(filters, "SELECT unnest(range(0, n + 4, 4)) AS t FROM total") + f" SELECT *, {cost} FROM counted")
        _add(f"slices_read_{kind}", lambda spark, sf, filters=filters: (lambda s: s.io_by_strategy(s.search(**filters), 1e-4))(wl.store(spark, sf, "fact5")))
        for strategy in ("crawl", "hybrid"):
            _add(f"count_by_{strategy}_{kind}", lambda spark, sf, filters=filters, strategy=strategy: wl.store(spark, sf, "fact5").count_where(strategy, 1e-4, **filters), sql.replace("matched", "count"))


def _race(spark: SparkSession, sf: str, filters: dict[str, Filter]) -> DataFrame:
    """Both theoretical thresholds and the chosen one beside the pure strategies."""
    s = wl.store(spark, sf, "fact5")
    search = s.search(**filters)
    c, n = s.rows, s.layout.n
    thresholds = {"crawl": n, "leap": 0, "hybrid_rows": costs.threshold_cardinality(n, c, RATIO, search.mask), "hybrid_gaps": costs.threshold_lacuna(search, c, RATIO), "hybrid": costs.choose_threshold(search, c, RATIO).threshold}
    return race(s, search, RATIO, thresholds)


def _sweep(spark: SparkSession, sf: str, filters: dict[str, Filter]) -> DataFrame:
    """Counters and cost for thresholds from 0 to n in steps of 4."""
    s = wl.store(spark, sf, "fact5")
    search = s.search(**filters)
    return declarative_counters(s.data, s.layout.key_columns, search, list(range(0, s.layout.n + 4, 4))).withColumn("cost", F.col("scans") * RATIO + F.col("jumps"))


def layout_comparison(spark: SparkSession, sf: str) -> DataFrame:
    """For every layout and attribute of the five-attribute table: slices kept by a point, and costs of the strategies.

    Both follow from the keys, so the stores hold the keys of all rows and no other columns.
    """
    out = []
    df = fact(spark, sf, "fact5")
    value = df.orderBy(F.xxhash64(*df.columns)).first().asDict()
    for kind in ("interleave", "junior", "odometer", "blocked2", "blocked4"):
        s = wl.store(spark, sf, "fact5", layout=kind, keys_only=True)
        slices, n, c = len(s.listed()), s.layout.n, s.rows
        searches = {}
        for a in FACTS["fact5"]:
            v = value[a].date() if hasattr(value[a], "date") else value[a]
            search = s.search(**{a: Eq(round(v, 2) if isinstance(v, float) else v)})
            searches[a] = (search, [0, costs.choose_threshold(search, c, RATIO).threshold, n])
        for a, counted in points_counters(s.data, searches).items():
            search, (_, t, _) = searches[a]
            got = {x: scans * RATIO + jumps for x, (_, scans, jumps) in counted.items()}
            out.append((kind, a, slices, len(s.decisions(search)), t, float(got[n]), float(got[0]), float(got[t])))
    return _rows(spark, out, "layout string, attribute string, slices bigint, kept bigint, threshold int, crawl double, leap double, hybrid double")


def average_cost(spark: SparkSession, sf: str) -> DataFrame:
    """Over all patterns of a mask, for every attribute and every pair: total jumps and scans, and what the theory says of them."""
    s = wl.store(spark, sf, "fact5")
    n, c = s.layout.n, s.rows
    out = []
    masks = {",".join(names): sum(map(s.layout.mask, names)) for k in (1, 2) for names in itertools.combinations(FACTS["fact5"], k)}
    of_mask = list(masks.values())
    totals = averages(s.data, {mask: costs.threshold_cardinality(n, c, RATIO, mask) for mask in of_mask}, n)
    seconds, sigmas = costs.r2s(s.data, of_mask, n), region_sigmas(s.data, of_mask, n)
    for a, mask in masks.items():
        d = mask.bit_count()
        got = totals[mask]
        jumps = got["leap_jumps"]
        second, sigma = seconds[mask], sigmas[mask]
        counted = map(Decimal, (jumps, got["crawl_scans"], got["hybrid_jumps"], got["hybrid_scans"], costs.crawl_total(d, c)))
        out.append((a, d, *counted, costs.jump_bound(mask, n) >= jumps, float(costs.r1(mask, n, c)), second, costs.r2_uniform(d, n), float(min(costs.r2_eps(mask, n, sigma), 1e300)), sigma, costs.sigma0(mask, n), costs.leap_wins_exact(jumps, RATIO, d, c)))
    counters = ", ".join(f"{x} decimal(38,0)" for x in ("leap_jumps", "crawl_scans", "hybrid_jumps", "hybrid_scans", "crawl_total"))  # patterns times rows can be more than a long holds
    return _rows(spark, out, f"attribute string, d int, {counters}, bound_holds boolean, r1 double, r2 double, r2_uniform double, r2_bound double, sigma double, sigma0 double, leap_wins boolean")


def verdicts(spark: SparkSession, sf: str) -> DataFrame:
    """Per attribute: the ratios above which jumping is proven to win, thresholds and useful bits."""
    s = wl.store(spark, sf, "fact5")
    n, c = s.layout.n, s.rows
    out = []
    for a in FACTS["fact5"]:
        m = s.layout.mask(a)
        x, y = float(costs.r1(m, n, c)), costs.r2(s.data, m, n)
        even = costs.even_enough(costs.region_sigma(s.data, m, n), m, n)
        out.append((a, m.bit_count(), x, y, even, costs.verdict(RATIO, x, y), costs.useful_bits(c, RATIO), costs.threshold_cardinality(n, c, RATIO, m), costs.break_even(RATIO)))
    return _rows(spark, out, "attribute string, d int, r1 double, r2 double, even_enough boolean, leap_wins boolean, useful_bits double, threshold int, break_even double")


def lacuna_lengths(spark: SparkSession, sf: str) -> DataFrame:
    """Per attribute: clusters of a point search, their length, all gaps, and the possible gap lengths."""
    layout = wl.store(spark, sf, "fact5").layout
    out = []
    for a in FACTS["fact5"]:
        m = layout.mask(a)
        clusters, length = geometry.point_clusters(m, layout.n)
        out.append((a, clusters, length, geometry.point_gap_total(m, layout.n), geometry.point_gaps(m)))
    return _rows(spark, out, "attribute string, clusters bigint, cluster_length bigint, gap_total bigint, gaps array<bigint>")


def _measures() -> None:
    _add("layout_comparison", layout_comparison)
    _add("avg_cost_per_mask", average_cost)
    _add("r1_r2_verdicts", verdicts)
    _add("lacuna_lengths", lacuna_lengths, oracles.lacunae_sql())
    _add("region_distribution", lambda spark, sf: (lambda s: s.data.groupBy(F.shiftright("k0", s.layout.n - 8).alias("region")).agg(F.count(F.lit(1)).alias("rows")))(wl.store(spark, sf, "fact5")), oracles.regions_sql(8))
    _add("layout_report", lambda spark, sf: (lambda s: _rows(spark, [tuple(r.values()) for r in s.layout.report(round(costs.useful_bits(s.rows, RATIO)))], "attribute string, bits int, head int, tail int, useful int"))(wl.store(spark, sf, "fact16")))
    _add("cofrequency", lambda spark, sf: (lambda s: s.data.agg(F.avg(costs.cofrequency_column(F.col("k0"), s.layout.mask("l_discount"), s.layout.n)).alias("mean_cofrequency")))(wl.store(spark, sf, "fact5")), oracles.cofrequency_sql("l_discount"))
    _add("next_match_present_key", next_match_present, "SELECT CAST(0 AS BIGINT) AS differ, count(*) AS keys FROM lineitem")


def next_match_present(spark: SparkSession, sf: str) -> DataFrame:
    """Rows whose next match as a bit expression for points differs from that of the matchers for all kinds: none."""
    s = wl.store(spark, sf, "fact5")
    search = s.search(l_quantity=Eq(9.0), l_discount=Eq(0.03))
    both = with_next_match(s.data.select("k0", search.next_match_column(F.col("k0")).alias("a")), ["k0"], search, "y", ["b"])
    return both.agg(F.count_if(~F.col("a").eqNullSafe(F.col("b"))).alias("differ"), F.count(F.lit(1)).alias("keys"))


def _stores() -> None:
    sql = lambda f: f"SELECT count(*) AS count FROM lineitem WHERE {wl.where_sql(f)}"
    two = {"l_quantity": Eq(11.0), "l_discount": Eq(0.05)}
    _add("aligned_count", lambda spark, sf: wl.store(spark, sf, "fact5", aligned=True).count_where(**two), sql(two))
    for kind in ("junior", "odometer", "blocked2", "blocked4", "last:l_discount"):
        _add(f"layout_{kind.replace(':', '_')}_count", lambda spark, sf, kind=kind: wl.store(spark, sf, "fact5", layout=kind).count_where(**two), sql(two))
    for n in (4, 16, 64, 128):
        _add(f"slices_{n}_count", lambda spark, sf, n=n: wl.store(spark, sf, "fact5", slices=n).count_where(**two), sql(two))
    _add("slice_catalog", lambda spark, sf: wl.store(spark, sf, "fact5").catalog.agg(F.sum("rows").alias("rows")), "SELECT CAST(count(*) AS BIGINT) AS rows FROM lineitem")
    _add("slice_classify", lambda spark, sf: (lambda s: s.classify(s.search(**two), RATIO))(wl.store(spark, sf, "fact5")))
    _add("slice_io_report", lambda spark, sf: (lambda s: s.io_report(s.search(**two)))(wl.store(spark, sf, "fact5")))
    _add("per_slice_counters", lambda spark, sf: (lambda s: cursor_counters(s, s.search(l_quantity=Eq(17.0)), s.layout.n // 2))(wl.store(spark, sf, "fact5", slices=128)))
    last = {"l_linestatus": Eq("F")}
    _add("whole_slice_count", lambda spark, sf: wl.store(spark, sf, "fact10", aligned=True).count_where(**last), sql(last))
    _add("count_not_in", lambda spark, sf: wl.store(spark, sf, "fact5").count_where(l_quantity=NotIn((1.0, 2.0, 3.0))), "SELECT count(*) AS count FROM lineitem WHERE l_quantity NOT IN (1, 2, 3)")
    _add("count_any_of", lambda spark, sf: wl.store(spark, sf, "fact5").count_where(l_quantity=AnyOf((Eq(4.0), Between(20.0, 24.0)))), "SELECT count(*) AS count FROM lineitem WHERE l_quantity = 4 OR l_quantity BETWEEN 20 AND 24")
    _add("count_or_across", lambda spark, sf: wl.store(spark, sf, "fact5").count_any({"l_quantity": Eq(7.0)}, {"l_suppkey": Eq(3)}), "SELECT count(*) AS count FROM lineitem WHERE l_quantity = 7 OR l_suppkey = 3")
    _add("count_prefix", lambda spark, sf: wl.store(spark, sf, "fact16").count_where(p_brand=Prefix("Brand#2")), f"SELECT count(*) AS count FROM ({STAR_SQL}) f WHERE p_brand LIKE 'Brand#2%'")
    _add("count_is_null", lambda spark, sf: wl.store(spark, sf, "doc5").count_where(quality=IsNull()), "SELECT count(*) AS count FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE l.quality IS NULL")
    _add("count_binned", lambda spark, sf: wl.store(spark, sf, "doc5").count_where(n_chars=Between(300, 1200), lang=Eq("en")), "SELECT count(*) AS count FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE n_chars BETWEEN 300 AND 1200 AND lang = 'en'")
    _add("count_empty", lambda spark, sf: wl.store(spark, sf, "fact5").count_where(l_quantity=Eq(1000.0)), sql({"l_quantity": Eq(1000.0)}))
    _add("where_rows", lambda spark, sf: wl.store(spark, sf, "fact5").where(["l_partkey", "l_suppkey", "l_extendedprice"], **two), f"SELECT l_partkey, l_suppkey, l_extendedprice FROM lineitem WHERE {wl.where_sql(two)}")
    _add("residual_measure", lambda spark, sf: wl.store(spark, sf, "fact5").where(**two).where("l_extendedprice > 20000").agg(F.count(F.lit(1)).alias("count")), sql(two) + " AND l_extendedprice > 20000")
    many = {"a": {"l_quantity": Eq(3.0)}, "b": {"l_suppkey": Eq(4)}, "c": {"l_discount": Between(0.02, 0.03)}, "d": {"l_partkey": Between(5, 50)}}
    _add("cooperative_counts", lambda spark, sf: wl.store(spark, sf, "fact5").count_many(many), " UNION ALL ".join(f"SELECT '{k}' AS name, count(*) AS count FROM lineitem WHERE {wl.where_sql(f)}" for k, f in many.items()))
    _add("crosstab_where", lambda spark, sf: wl.store(spark, sf, "fact16").crosstab("c_mktsegment", "o_orderpriority", p_size=Between(10, 20)), f"SELECT c_mktsegment, o_orderpriority, count(*) AS count FROM ({STAR_SQL}) f WHERE p_size BETWEEN 10 AND 20 GROUP BY 1, 2")
    _add("first_in_key_order", lambda spark, sf: wl.store(spark, sf, "fact5").first(25, l_quantity=Eq(17.0)).select("k0"), oracles.first_sql({"l_quantity": Eq(17.0)}, 25))
    _add("compacted_count", lambda spark, sf: wl.store(spark, sf, "fact5").compact(Scratch(spark, "compact").root, 8).count_where(**two), sql(two))
    _add("encode_roundtrip", lambda spark, sf: _roundtrip(spark, sf, "fact5"), "SELECT CAST(0 AS BIGINT) AS differ, count(*) AS rows FROM lineitem")
    _add("wide_key_roundtrip", lambda spark, sf: _roundtrip(spark, sf, "fact18"), "SELECT CAST(0 AS BIGINT) AS differ, count(*) AS rows FROM lineitem")
    _add("dictionary_ordered", lambda spark, sf: build_dictionary(table(spark, sf, "part"), "p_brand"), "SELECT p_brand AS value, row_number() OVER (ORDER BY p_brand) AS code FROM (SELECT DISTINCT p_brand FROM part)")
    _add("dictionary_unordered", lambda spark, sf: build_dictionary(table(spark, sf, "part"), "p_type", ordered=False).agg(F.count_distinct("code").alias("codes"), F.min("code").alias("low"), F.max("code").alias("high")), "SELECT count(DISTINCT p_type) AS codes, CAST(1 AS BIGINT) AS low, count(DISTINCT p_type) AS high FROM part")
    _add("sql_front_end", _sql_front, "SELECT count(*) AS count FROM lineitem WHERE l_quantity = 11 AND l_suppkey IN (2, 4, 6)")
    _add("split_values_count", _split_values, f"SELECT count(*) AS count, CAST(sum(CAST(l_extendedprice AS DECIMAL(15,2))) AS DOUBLE) AS total FROM lineitem WHERE {wl.where_sql(two)}")
    _add("crawl_region_count", crawl_region_count, sql(two))
    for kind in ("json", "csv", "orc"):
        _add(f"export_{kind}", lambda spark, sf, kind=kind: exported(spark, sf, kind), "SELECT p_partkey, p_name, p_size FROM part")
    _add("same_bag", lambda spark, sf: _same_bag(spark, sf, two), "SELECT CAST(0 AS BIGINT) AS only_store, CAST(0 AS BIGINT) AS only_scan")


def _roundtrip(spark: SparkSession, sf: str, name: str) -> DataFrame:
    df = fact(spark, sf, name)
    layout = wl.layout_of(df, name, "interleave")
    wrong = F.lit(False)
    for a in layout.attributes:
        wrong = wrong | (layout.code_expression(a.name) != a.codec.column(F.col(a.name)))
    return layout.encode(df).agg(F.count_if(wrong).alias("differ"), F.count(F.lit(1)).alias("rows"))


def _sql_front(spark: SparkSession, sf: str) -> DataFrame:
    from keyhop.sources.datasource import register

    register(spark)
    s = wl.store(spark, sf, "fact5")
    spark.read.format("keyhop").load(s.path).createOrReplaceTempView("keyhop_fact5")
    return spark.sql("SELECT count(*) AS count FROM keyhop_fact5 WHERE l_quantity = 11.0 AND l_suppkey IN (2, 4, 6)")


def _split_values(spark: SparkSession, sf: str) -> DataFrame:
    """Keys and dimensions apart from the measure, joined by slice and row number after the filter."""
    s = wl.store(spark, sf, "fact5")
    from pyspark.sql import Window

    numbered = s.data.withColumn("row", F.row_number().over(Window.partitionBy("slice").orderBy("k0", F.xxhash64(*s.data.columns))))
    scratch = Scratch(spark, "split")
    keys = scratch.save(numbered.drop("l_extendedprice"), "keys")
    values = scratch.save(numbered.select("slice", "row", "l_extendedprice"), "values")
    hit = keys.where(condition(s.layout, {"l_quantity": Eq(11.0), "l_discount": Eq(0.05)})).select("slice", "row")
    return hit.join(values, ["slice", "row"]).agg(F.count(F.lit(1)).alias("count"), F.sum(F.col("l_extendedprice").cast("decimal(15,2)")).cast("double").alias("total"))


def _same_bag(spark: SparkSession, sf: str, filters: dict[str, Filter]) -> DataFrame:
    s = wl.store(spark, sf, "fact5")
    a = s.where(list(FACTS["fact5"]), **filters)
    b = fact(spark, sf, "fact5").where(condition(s.layout, filters)).select(*FACTS["fact5"])
    left, right = a.exceptAll(b).agg(F.count(F.lit(1)).alias("only_store")), b.exceptAll(a).agg(F.count(F.lit(1)).alias("only_scan"))
    return left.crossJoin(right)  # one row each


def crawl_region_count(spark: SparkSession, sf: str) -> DataFrame:
    """Crawl regions from a table function, joined to the rows by their prefix, with the condition tested on each row."""
    from pyspark.sql.functions import udtf

    from keyhop.plans.search import crawl_intervals
    from keyhop.runtime import ship

    ship(spark)
    s = wl.store(spark, sf, "fact5")
    filters = {"l_quantity": Eq(11.0), "l_discount": Eq(0.05)}
    search = s.search(**filters)
    threshold = s.layout.n - 10

    class Regions:
        def eval(self, t: int):
            yield from crawl_intervals(search, t)

    regions = udtf(Regions, returnType="lo bigint, hi bigint")(F.lit(threshold)).select(F.shiftright("lo", threshold).alias("prefix"))
    rows = s.data.withColumn("prefix", F.shiftright("k0", threshold))
    return rows.join(F.broadcast(regions), "prefix").where(condition(s.layout, filters)).agg(F.count(F.lit(1)).alias("count"))  # at most 2^10 regions


def exported(spark: SparkSession, sf: str, kind: str) -> DataFrame:
    """The parts, written in another format and read back with their schema."""
    parts = table(spark, sf, "part").select("p_partkey", "p_name", "p_size")
    path = Scratch(spark, "export").path(kind)
    parts.write.format(kind).option("header", "true").save(path)
    return spark.read.schema(parts.schema).format(kind).option("header", "true").load(path)


def _baselines() -> None:
    f = {"p_brand": Eq("Brand#12"), "p_size": Between(10, 20), "o_orderpriority": Eq("1-URGENT")}
    sql = f"SELECT count(*) AS count FROM ({STAR_SQL}) f WHERE {wl.where_sql(f)}"
    _add("base_fullscan_star", lambda spark, sf: fact(spark, sf, "fact16").where(condition(None, f)).agg(F.count(F.lit(1)).alias("count")), sql)
    g = {"l_suppkey": Eq(4), "l_quantity": Between(5.0, 9.0)}
    one = f"SELECT count(*) AS count FROM lineitem WHERE {wl.where_sql(g)}"
    _add("base_fullscan", lambda spark, sf: table(spark, sf, "lineitem").where(condition(None, g)).agg(F.count(F.lit(1)).alias("count")), one)

    def by_order(spark: SparkSession, sf: str, attribute: str) -> DataFrame:
        lines = table(spark, sf, "lineitem").select(*FACTS["fact5"])
        ordered = Scratch(spark, "sorted").save(lines.repartitionByRange(16, attribute, F.xxhash64(*lines.columns)).sortWithinPartitions(attribute), "lines")
        return ordered.where(condition(None, g)).agg(F.count(F.lit(1)).alias("count"))

    _add("base_sorted_leading", lambda spark, sf: by_order(spark, sf, "l_suppkey"), one)
    _add("base_sorted_other", lambda spark, sf: by_order(spark, sf, "l_partkey"), one)

    def partitioned(spark: SparkSession, sf: str) -> DataFrame:
        path = Scratch(spark, "partitioned").path("lines")
        table(spark, sf, "lineitem").select("l_suppkey", "l_quantity", "l_returnflag").write.partitionBy("l_returnflag").parquet(path)
        return spark.read.parquet(path).where("l_returnflag = 'R' and l_quantity = 9").agg(F.count(F.lit(1)).alias("count"))

    _add("base_partitioned", partitioned, "SELECT count(*) AS count FROM lineitem WHERE l_returnflag = 'R' AND l_quantity = 9")

    def cube(spark: SparkSession, sf: str) -> DataFrame:
        """A materialised cube over three dimensions answers filters on those alone."""
        built = table(spark, sf, "lineitem").cube("l_returnflag", "l_linestatus", "l_quantity").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("g"))
        kept = Scratch(spark, "cube").save(built, "cube")
        return kept.where("g = 2 and l_returnflag = 'R' and l_quantity = 9").agg(F.sum("n").alias("count"))

    _add("base_materialized_cube", cube, "SELECT CAST(count(*) AS BIGINT) AS count FROM lineitem WHERE l_returnflag = 'R' AND l_quantity = 9")


def gain_by_restrictions(spark: SparkSession, sf: str) -> DataFrame:
    """Costs relative to crawl by the number of restrictions."""
    s = wl.store(spark, sf, "fact5")
    out = []
    for k in (1, 2, 3):
        for w in wl.mixes("fact5", "P" * k, 4):
            search = s.search(**w.filters)
            if search.empty or not search.point:
                continue
            t = costs.choose_threshold(search, s.rows, RATIO).threshold
            got = {r["threshold"]: r["scans"] * RATIO + r["jumps"] for r in point_counters(s.data, search, sorted({0, t, s.layout.n})).collect()}
            kept = sum(n for _, n, _ in s.decisions(search))
            out.append((k, w.name, float(got[s.layout.n]), float(got[0]), float(got[t]), kept))
    return _rows(spark, out, "k int, name string, crawl double, leap double, hybrid double, rows_in_kept_slices bigint")


def every_combination(spark: SparkSession, sf: str) -> DataFrame:
    """All searches on up to three of the 16 attributes, each by point, range or set: what the strategies read, on average.

    One row for each mix of kinds: number of searches, mean share of the slices read by crawl, leap and
    hybrid, and mean share of the rows that leap takes from the catalog. Searches are dealt to tasks,
    each with the listed catalog.
    """
    from keyhop.runtime import ship

    ship(spark)
    s = wl.store(spark, sf, "fact16")
    listed, layout = s.listed(), s.layout
    rows = [("".join(kinds), ",".join(names)) for k in (1, 2, 3) for names in itertools.combinations(FACTS["fact16"], k) for kinds in itertools.product("PRS", repeat=k)]
    total = sum(r[1] for r in listed)
    local = KeyedStore(None, "", layout, _listed=(listed,))

    def run(batches):
        import random

        import pyarrow as pa

        for batch in batches:
            out = []
            for kinds, names in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                rng = random.Random(f"{kinds}-{names}")
                search = local.search(**{n: wl.draw(rng, n, k) for n, k in zip(names.split(","), kinds, strict=True)})
                found = {x: local.decisions(search, x, 1e-4) for x in ("crawl", "leap", "hybrid")}
                read = [sum(a != "whole" for _, _, a in found[x]) / len(listed) for x in ("crawl", "leap", "hybrid")]
                out.append(("".join(sorted(kinds)), *read, sum(n for _, n, a in found["leap"] if a == "whole") / total))
            columns_ = list(zip(*out, strict=True)) if out else [[]] * 5
            yield pa.RecordBatch.from_arrays([pa.array(columns_[0], pa.string()), *(pa.array(c, pa.float64()) for c in columns_[1:])], ["kinds", "crawl", "leap", "hybrid", "counted"])

    searches = spark.createDataFrame(rows, "kinds string, names string").repartition(64)
    read = searches.mapInArrow(run, "kinds string, crawl double, leap double, hybrid double, counted double")
    return read.groupBy("kinds").agg(F.count(F.lit(1)).alias("searches"), *(F.round(F.avg(c), 9).alias(c) for c in ("crawl", "leap", "hybrid", "counted")))


def _many_points(name: str) -> None:
    """Points on one to five random attributes, 20 draws each: all counts in one scan, and what the strategies read."""
    draws = {w.name: w for w in wl.points(name, 5, 20)}
    one = " UNION ALL ".join(f"SELECT '{k}' AS name, count(*) FILTER (WHERE {wl.where_sql(w.filters)}) AS count FROM f" for k, w in draws.items())
    _add(f"points_{name}", lambda spark, sf: wl.store(spark, sf, name).count_many({k: w.filters for k, w in draws.items()}), f"WITH f AS ({wl.fact_sql(name)}) {one}")

    def read(spark: SparkSession, sf: str) -> DataFrame:
        s = wl.store(spark, sf, name)
        out = []
        for w in draws.values():
            search = s.search(**w.filters)
            shares = [sum(a != "whole" for _, _, a in s.decisions(search, x, 1e-4)) / len(s.listed()) for x in ("crawl", "leap", "hybrid")]
            out.append((len(w.filters), *shares))
        return _rows(spark, out, "k int, crawl double, leap double, hybrid double").groupBy("k").agg(F.count(F.lit(1)).alias("searches"), *(F.round(F.avg(c), 9).alias(c) for c in ("crawl", "leap", "hybrid")))

    _add(f"points_{name}_read", read)


def store_variants(spark: SparkSession, sf: str, filters: dict[str, Filter]) -> DataFrame:
    """The same count from one sorted file with small row groups, from many slices, from slices with small row groups, and from a cached sorted batch."""
    one, many, groups = (wl.store(spark, sf, "fact5", slices=n, row_group_rows=g) for n, g in ((1, 2000), (32, None), (32, 500)))
    out = None
    for name, s in (("one_file", one), ("slices", many), ("row_groups", groups)):
        got = s.count_where("hybrid", 1e-3, **filters).select(F.lit(name).alias("variant"), "count")
        out = got if out is None else out.union(got)
    held = one.data.select("k0").sortWithinPartitions("k0").cache()
    return out.union(leap_counters(held, ["k0"], one.search(**filters)).select(F.lit("cached_batch"), "matched"))


def _sweep_of(name: str, filters: dict[str, Filter]) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        s = wl.store(spark, sf, name)
        return declarative_counters(s.data, s.layout.key_columns, s.search(**filters), list(range(0, s.layout.n + 8, 8))).withColumn("cost", F.col("scans") * RATIO + F.col("jumps"))

    return run


def junior_bit(spark: SparkSession, sf: str) -> DataFrame:
    """A point on the most junior attribute: leap jumps at nearly every row, hybrid falls back to scanning."""
    s = wl.store(spark, sf, "fact5", layout="last:l_discount")
    search = s.search(l_discount=Eq(0.05))
    n = s.layout.n
    return race(s, search, RATIO, {"crawl": n, "leap": 0, "hybrid": costs.choose_threshold(search, s.rows, RATIO).threshold})


def uneven_slices(spark: SparkSession, sf: str) -> DataFrame:
    """Counters per slice where one supplier range is over-represented."""
    df = fact(spark, sf, "fact5")
    skewed = df.union(df.where("l_suppkey <= 2")).union(df.where("l_suppkey <= 2"))
    s = KeyedStore.build(skewed, wl.layout_of(df, "fact5", "interleave"), Scratch(spark, "uneven").root, 16, aligned=True)
    return cursor_counters(s, s.search(l_quantity=Eq(17.0)), s.layout.n // 2).join(s.catalog.select("slice", "rows"), "slice")


def _experiments() -> None:
    _add("gain_by_restrictions", gain_by_restrictions)
    _add("every_combination", every_combination)
    for name in ("fact5", "fact10"):
        _many_points(name)
    two = {"l_quantity": Eq(11.0), "l_discount": Eq(0.05)}
    sql = f"SELECT count(*) AS count FROM lineitem WHERE {wl.where_sql(two)}"
    variants = ("one_file", "slices", "row_groups", "cached_batch")
    _add("store_variants", lambda spark, sf: store_variants(spark, sf, two), " UNION ALL ".join(sql.replace("SELECT", f"SELECT '{v}' AS variant,", 1) for v in variants))
    for rows in (500, 4000):
        _add(f"row_groups_{rows}_count", lambda spark, sf, rows=rows: wl.store(spark, sf, "fact5", slices=4, row_group_rows=rows).count_where("hybrid", 1e-3, **two), sql)
    _add("shortened_keys_count", lambda spark, sf: wl.store(spark, sf, "fact5").count_shortened(**two), sql)
    _add("shortened_keys", lambda spark, sf: wl.store(spark, sf, "fact5").shortened())
    _add("threshold_sweep_fact10", _sweep_of("fact10", {"l_quantity": Eq(17.0), "o_orderpriority": Eq("2-HIGH")}))
    _add("threshold_sweep_fact16", _sweep_of("fact16", {"l_quantity": Eq(17.0), "p_size": Between(10, 20)}))
    _add("per_slice_fact16", lambda spark, sf: (lambda s: cursor_counters(s, s.search(l_quantity=Eq(17.0)), s.layout.n // 2))(wl.store(spark, sf, "fact16", slices=128)))
    _add("junior_bit_worst_case", junior_bit)
    _add("uneven_slices", uneven_slices)
    from keyhop.calibrate import calibrate_query

    _add("calibrate_ratio", calibrate_query)


def _streams() -> None:
    # Complete mode: at the source's end, windows that the watermark has not closed are given too.
    every = lambda grouped, *names: lambda spark, sf: finished(grouped(event_stream(spark, sf)).agg(F.count(F.lit(1)).alias("n")).select(*names, "n"), Scratch(spark, "stream").root, "complete")
    start = "w.start"
    _add("stream_tumbling", every(lambda e: e.groupBy(F.window("ts", "1 day").alias("w"), "event_type"), start, "event_type"), "SELECT date_trunc('day', CAST(ts AS TIMESTAMP)) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
    _add("stream_sliding", every(lambda e: e.groupBy(F.window("ts", "2 days", "1 day").alias("w")), start), "SELECT date_trunc('day', CAST(ts AS TIMESTAMP)) - to_days(CAST(back AS INTEGER)) AS start, count(*) AS n FROM events, range(2) r(back) GROUP BY 1")
    _add("stream_session", every(lambda e: e.groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id"), "user_id"), SESSIONS)
    _add("stream_dedup", lambda spark, sf: finished(event_stream(spark, sf).dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"), Scratch(spark, "stream").root), "SELECT DISTINCT event_id, user_id FROM events")
    _add("stream_static_join", lambda spark, sf: finished(event_stream(spark, sf).join(table(spark, sf, "nation"), F.col("user_id") == F.col("n_nationkey")).select("event_id", "n_name"), Scratch(spark, "stream").root), "SELECT event_id, n_name FROM events JOIN nation ON user_id = n_nationkey")
    _add("stream_stream_join", stream_joined, "SELECT a.event_id AS viewed, b.event_id AS clicked FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'click' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 60 MINUTE")
    _add("stream_stateful_counts", stream_counts, "SELECT user_id, count(*) AS n FROM events GROUP BY 1")
    _add("stream_keyed_store", stream_keyed, "SELECT count(*) AS count FROM events WHERE event_type = 'click' AND CAST(ts AS DATE) BETWEEN DATE '2024-01-05' AND DATE '2024-01-15'")


#: A session ends where no event of the user follows within 30 minutes.
SESSIONS = """WITH marked AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS opens FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
numbered AS (SELECT user_id, sum(opens) OVER (PARTITION BY user_id ORDER BY ts) AS session FROM marked)
SELECT user_id, count(*) AS n FROM numbered GROUP BY user_id, session"""


def stream_joined(spark: SparkSession, sf: str) -> DataFrame:
    """Clicks within an hour of a view by the same user, both sides streams."""
    a = event_stream(spark, sf).where("event_type = 'view'").select(F.col("event_id").alias("viewed"), F.col("user_id").alias("u"), F.col("ts").alias("from"))
    b = event_stream(spark, sf).where("event_type = 'click'").select(F.col("event_id").alias("clicked"), F.col("user_id").alias("v"), F.col("ts").alias("to"))
    return finished(a.join(b, F.expr("u = v AND to > from AND to <= from + interval 60 minutes")).select("viewed", "clicked"), Scratch(spark, "stream").root)


def stream_counts(spark: SparkSession, sf: str) -> DataFrame:
    """Running count per user by a stateful operator; the last value of each user."""
    import pandas as pd

    def run(key, frames, state):
        n = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n]})

    counted = event_stream(spark, sf).select("user_id", "event_id").groupBy("user_id").applyInPandasWithState(run, "user_id bigint, n bigint", "n bigint", "append", "NoTimeout")
    return finished(counted, Scratch(spark, "stream").root).groupBy("user_id").agg(F.max("n").alias("n"))


def stream_keyed(spark: SparkSession, sf: str) -> DataFrame:
    """The store fed by the event stream answers as the batch does."""
    layout = wl.layout_of(fact(spark, sf, "ev5"), "ev5", "interleave")
    root = Scratch(spark, "stream-store").root
    source = events(event_stream(spark, sf)).select("event_id", *FACTS["ev5"])
    return stream_store(source, layout, f"{root}/store", f"{root}/state").count_where(event_type=Eq("click"), day=Between(dt.date(2024, 1, 5), dt.date(2024, 1, 15)))


def _register() -> None:
    _counts()
    _contest()
    _strategies()
    _measures()
    _stores()
    _baselines()
    _experiments()
    _streams()
    for name, (query, sql) in all_operators().items():
        _add(name, query, sql)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A count with two point filters from the keyed store."""
    return wl.store(spark, sf_dir, "fact5").count_where(l_quantity=Eq(11.0), l_discount=Eq(0.05))


def queries() -> dict[str, Query]:
    if not _Q:
        _register()
    return dict(_Q)


def oracle_sql() -> dict[str, str]:
    queries()
    return dict(_SQL)


