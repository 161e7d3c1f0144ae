"""The relational operators around the store, each as a query with the same result in SQL."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from keyhop.runtime import ship, table

Query = Callable[[SparkSession, str], DataFrame]
_ALL: dict[str, tuple[Query, str]] = {}


def op(name: str, sql: str):
    """Register a query (given the table reader) with its SQL."""

    def add(fn):
        _ALL[f"op_{name}"] = (lambda spark, sf: fn(lambda n: table(spark, sf, n)), sql)
        return fn

    return add


def all_operators() -> dict[str, tuple[Query, str]]:
    return dict(_ALL)


def _n() -> object:
    return F.count(F.lit(1)).cast("bigint")


def _sums(batches):
    """Sums of a batch by group, for a least-squares line."""
    for b in batches:
        x, y = b["l_quantity"], b["l_extendedprice"]
        out = b.assign(n=1.0, x=x, y=y, xx=x * x, xy=x * y).groupby("l_returnflag", as_index=False)[["n", "x", "y", "xx", "xy"]].sum()
        yield out


def _slope(n: pd.Series, x: pd.Series, y: pd.Series, xx: pd.Series, xy: pd.Series) -> float:
    n, x, y, xx, xy = (float(s.sum()) for s in (n, x, y, xx, xy))
    return (xy / n - x / n * y / n) / (xx / n - (x / n) ** 2)


@op("project_computed", "SELECT l_orderkey, l_linenumber, CAST(l_quantity AS BIGINT) * 2 AS twice FROM lineitem")
def _(t):
    return t("lineitem").select("l_orderkey", "l_linenumber", (F.col("l_quantity").cast("bigint") * 2).alias("twice"))


@op("filter_or_across", "SELECT count(*) AS n FROM lineitem WHERE l_quantity = 7 OR l_suppkey = 3")
def _(t):
    return t("lineitem").where((F.col("l_quantity") == 7) | (F.col("l_suppkey") == 3)).agg(_n().alias("n"))


@op("filter_like_prefix", "SELECT count(*) AS n FROM part WHERE p_brand LIKE 'Brand#2%'")
def _(t):
    return t("part").where(F.col("p_brand").startswith("Brand#2")).agg(_n().alias("n"))


@op("filter_null", "SELECT count(*) AS n FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE l.quality IS NULL")
def _(t):
    return t("documents").select("doc_id").join(t("labels").select("doc_id", "quality"), "doc_id", "left").where("quality is null").agg(_n().alias("n"))


@op("join_star_broadcast", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def _(t):
    return t("customer").join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(_n().alias("n"))


@op("join_sort_merge", "SELECT o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def _(t):
    return t("lineitem").join(t("orders").hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(_n().alias("n"))


@op("join_shuffled_hash", "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def _(t):
    return t("orders").join(t("customer").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(_n().alias("n"))


@op("join_left_outer", "SELECT d.lang, count(l.doc_id) AS labelled, count(*) AS n FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id GROUP BY 1")
def _(t):
    l = t("labels").select(F.col("doc_id").alias("l_id"))  # noqa: E741
    return t("documents").join(l, F.col("doc_id") == F.col("l_id"), "left").groupBy("lang").agg(F.count("l_id").alias("labelled"), _n().alias("n"))


@op("join_right_outer", "SELECT count(l.doc_id) AS labelled, count(*) AS n FROM labels l RIGHT JOIN documents d ON d.doc_id = l.doc_id")
def _(t):
    l = t("labels").select(F.col("doc_id").alias("l_id"))  # noqa: E741
    return l.join(t("documents").select("doc_id"), F.col("doc_id") == F.col("l_id"), "right").agg(F.count("l_id").alias("labelled"), _n().alias("n"))


@op("join_full_outer", "SELECT count(c.c_custkey) AS customers, count(o.o_custkey) AS orders FROM customer c FULL JOIN (SELECT DISTINCT o_custkey FROM orders WHERE o_orderstatus = 'P') o ON c.c_custkey = o.o_custkey")
def _(t):
    o = t("orders").where("o_orderstatus = 'P'").select("o_custkey").distinct()
    return t("customer").select("c_custkey").join(o, F.col("c_custkey") == F.col("o_custkey"), "full").agg(F.count("c_custkey").alias("customers"), F.count("o_custkey").alias("orders"))


@op("join_left_semi", "SELECT count(*) AS n FROM lineitem WHERE l_partkey IN (SELECT p_partkey FROM part WHERE p_brand = 'Brand#12')")
def _(t):
    return t("lineitem").join(t("part").where("p_brand = 'Brand#12'"), F.col("l_partkey") == F.col("p_partkey"), "left_semi").agg(_n().alias("n"))


@op("join_left_anti", "SELECT count(*) AS n FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_custkey IS NOT NULL)")
def _(t):
    return t("customer").join(t("orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").agg(_n().alias("n"))


@op("join_cross_small", "SELECT count(*) AS n FROM nation CROSS JOIN region")
def _(t):
    return t("nation").crossJoin(F.broadcast(t("region"))).agg(_n().alias("n"))


@op("join_theta_small", "SELECT count(*) AS n FROM nation a JOIN region r ON a.n_nationkey < r.r_regionkey")
def _(t):
    return t("nation").join(F.broadcast(t("region")), F.col("n_nationkey") < F.col("r_regionkey")).agg(_n().alias("n"))


@op("join_range_bucketed", "SELECT count(*) AS n FROM lineitem JOIN (SELECT p_partkey AS lo, p_partkey + 9 AS hi FROM part WHERE p_partkey % 40 = 0) i ON l_partkey BETWEEN lo AND hi")
def _(t):
    """Interval join as an equi-join on buckets wider than the intervals: an interval lies in two buckets at most."""
    rows = t("lineitem").select("l_partkey", F.floor(F.col("l_partkey") / 40).alias("bucket"))
    spans = t("part").where("p_partkey % 40 = 0").select(F.col("p_partkey").alias("lo"), (F.col("p_partkey") + 9).alias("hi"))
    spans = spans.withColumn("bucket", F.explode(F.sequence(F.floor(F.col("lo") / 40), F.floor(F.col("hi") / 40))))
    return rows.join(spans, "bucket").where(F.col("l_partkey").between(F.col("lo"), F.col("hi"))).agg(_n().alias("n"))


@op("join_as_of", "SELECT p.event_id, v.event_id AS last_view FROM events p ASOF LEFT JOIN (SELECT user_id, ts, event_id FROM events WHERE event_type = 'view') v ON p.user_id = v.user_id AND v.ts < p.ts WHERE p.event_type = 'purchase'")
def _(t):
    """Last earlier view of each purchase: one pass over each user's events in time order."""
    e = t("events").select("event_id", "user_id", "ts", "event_type")
    before = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, -1)
    micros = e.withColumn("ts", F.unix_micros(F.col("ts").cast("timestamp")))
    return micros.withColumn("last_view", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(before)).where("event_type = 'purchase'").select("event_id", "last_view")


@op("join_interval", "SELECT count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'click' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 60 MINUTE")
def _(t):
    a = t("events").where("event_type = 'view'").select("user_id", F.col("ts").alias("from"))
    b = t("events").where("event_type = 'click'").select("user_id", F.col("ts").alias("to"))
    return a.join(b, "user_id").where("to > from and to <= from + interval 60 minutes").agg(_n().alias("n"))


@op("agg_basic", "SELECT l_returnflag, count(*) AS n, round(sum(l_quantity), 2) AS total, round(avg(l_quantity), 4) AS mean, min(l_quantity) AS least, max(l_quantity) AS most FROM lineitem GROUP BY 1")
def _(t):
    q = F.col("l_quantity")
    return t("lineitem").groupBy("l_returnflag").agg(_n().alias("n"), F.round(F.sum(q), 2).alias("total"), F.round(F.avg(q), 4).alias("mean"), F.min(q).alias("least"), F.max(q).alias("most"))


@op("agg_variance", "SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS deviation, round(var_pop(l_quantity), 4) AS variance FROM lineitem GROUP BY 1")
def _(t):
    return t("lineitem").groupBy("l_returnflag").agg(F.round(F.stddev_samp("l_quantity"), 6).alias("deviation"), F.round(F.var_pop("l_quantity"), 4).alias("variance"))


@op("agg_count_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1")
def _(t):
    return t("lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


@op("agg_count_distinct_approx", "SELECT true AS close")
def _(t):
    return t("lineitem").agg((F.abs(F.approx_count_distinct("l_partkey", 0.02) - F.count_distinct("l_partkey")) <= 0.1 * F.count_distinct("l_partkey")).alias("close"))


@op("agg_median", "SELECT l_returnflag, median(l_quantity) AS middle FROM lineitem GROUP BY 1")
def _(t):
    return t("lineitem").groupBy("l_returnflag").agg(F.percentile("l_quantity", 0.5).alias("middle"))


@op("agg_percentiles_approx", "SELECT l_returnflag, true AS close FROM lineitem GROUP BY 1")
def _(t):
    """Approximate percentiles, by their ranks: at most one in a hundred off."""
    q = F.col("l_extendedprice")
    ends = t("lineitem").groupBy("l_returnflag").agg(F.percentile_approx(q, [0.1, 0.5, 0.9], 10_000).alias("p"), F.percentile(q, F.array(*map(F.lit, (0.09, 0.11, 0.49, 0.51, 0.89, 0.91)))).alias("e"))
    between = [F.col("p")[i].between(F.col("e")[2 * i], F.col("e")[2 * i + 1]) for i in range(3)]
    return ends.select("l_returnflag", (between[0] & between[1] & between[2]).alias("close"))


@op("agg_grouped_function", "SELECT l_returnflag, round(covar_pop(l_extendedprice, l_quantity) / var_pop(l_quantity), 6) AS slope FROM lineitem GROUP BY 1")
def _(t):
    """A grouped function over Arrow batches: the least-squares slope from sums of each batch, so that no group is held whole."""
    ship(t("lineitem").sparkSession)
    sums = t("lineitem").select("l_returnflag", "l_quantity", "l_extendedprice").mapInPandas(_sums, "l_returnflag string, n double, x double, y double, xx double, xy double")
    fit = F.pandas_udf(_slope, "double")
    return sums.groupBy("l_returnflag").agg(F.round(fit("n", "x", "y", "xx", "xy"), 6).alias("slope"))


@op("agg_grouping_sets", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def _(t):
    return t("lineitem").groupingSets([["l_returnflag"], ["l_linestatus"], []], "l_returnflag", "l_linestatus").agg(_n().alias("n"))


@op("agg_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def _(t):
    return t("lineitem").cube("l_returnflag", "l_linestatus").agg(_n().alias("n"))


@op("agg_rollup_hierarchy", "SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def _(t):
    d = t("nation").join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return t("customer").join(F.broadcast(d), F.col("c_nationkey") == F.col("n_nationkey")).rollup("r_name", "n_name").agg(_n().alias("n"))


@op("agg_conditional_having", "SELECT l_suppkey, count(*) FILTER (WHERE l_returnflag = 'R') AS returned FROM lineitem GROUP BY 1 HAVING count(*) FILTER (WHERE l_returnflag = 'R') > 10")
def _(t):
    return t("lineitem").groupBy("l_suppkey").agg(F.count_if(F.col("l_returnflag") == "R").alias("returned")).where("returned > 10")


@op("agg_pivot", "SELECT l_linestatus, count(*) FILTER (WHERE l_returnflag = 'A') AS A, count(*) FILTER (WHERE l_returnflag = 'N') AS N, count(*) FILTER (WHERE l_returnflag = 'R') AS R FROM lineitem GROUP BY 1")
def _(t):
    return t("lineitem").groupBy("l_linestatus").pivot("l_returnflag", ["A", "N", "R"]).agg(_n())


@op("agg_collect_set", "SELECT c_nationkey, array_to_string(list_sort(list(DISTINCT c_mktsegment)), ',') AS segments FROM customer GROUP BY 1")
def _(t):
    return t("customer").groupBy("c_nationkey").agg(F.array_join(F.array_sort(F.collect_set("c_mktsegment")), ",").alias("segments"))


@op("agg_max_by", "SELECT o_custkey, arg_max(o_orderkey, o_totalprice * 1000000 + o_orderkey / 1000000.0) AS dearest FROM orders GROUP BY 1")
def _(t):
    return t("orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.col("o_totalprice") * 1000000 + F.col("o_orderkey") / 1000000.0).alias("dearest"))


@op("window_ranks", "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER p AS rk, dense_rank() OVER p AS dr, ntile(4) OVER w AS nt FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderpriority, o_orderkey), p AS (PARTITION BY o_custkey ORDER BY o_orderpriority)")
def _(t):
    w, p = Window.partitionBy("o_custkey").orderBy("o_orderpriority", "o_orderkey"), Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return t("orders").select("o_orderkey", F.row_number().over(w).cast("bigint").alias("rn"), F.rank().over(p).cast("bigint").alias("rk"), F.dense_rank().over(p).cast("bigint").alias("dr"), F.ntile(4).over(w).cast("bigint").alias("nt"))


@op("window_percent_rank", "SELECT o_orderkey, round(percent_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderkey), 6) AS pr FROM orders")
def _(t):
    return t("orders").select("o_orderkey", F.round(F.percent_rank().over(Window.partitionBy("o_custkey").orderBy("o_orderkey")), 6).alias("pr"))


@op("window_lag_lead", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first, nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def _(t):
    w = Window.partitionBy("user_id").orderBy("event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return t("events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first"), F.nth_value("event_id", 2).over(whole).alias("second"))


@op("window_running", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 2) AS running, round(avg(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS moving FROM events")
def _(t):
    w = Window.partitionBy("user_id").orderBy("event_id")
    return t("events").select("event_id", F.round(F.sum("value").over(w.rowsBetween(Window.unboundedPreceding, 0)), 2).alias("running"), F.round(F.avg("value").over(w.rowsBetween(-2, 0)), 4).alias("moving"))


@op("window_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 50 PRECEDING AND CURRENT ROW) AS near FROM events")
def _(t):
    return t("events").select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy("event_id").rangeBetween(-50, 0)).alias("near"))


@op("sort_limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey DESC LIMIT 20 OFFSET 10")
def _(t):
    return t("orders").select("o_orderkey").orderBy(F.desc("o_orderkey")).offset(10).limit(20)


@op("top_per_group", "SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderkey DESC) AS k FROM orders) WHERE k <= 2")
def _(t):
    return t("orders").withColumn("k", F.row_number().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_orderkey")))).where("k <= 2").select("o_custkey", "o_orderkey")


@op("set_union_distinct", "SELECT l_suppkey AS k FROM lineitem UNION SELECT s_suppkey FROM supplier")
def _(t):
    return t("lineitem").select(F.col("l_suppkey").alias("k")).union(t("supplier").select("s_suppkey")).distinct()


@op("set_union_by_name", "SELECT n_nationkey AS k, n_name AS name FROM nation UNION ALL SELECT r_regionkey, r_name FROM region")
def _(t):
    return t("nation").select(F.col("n_nationkey").alias("k"), F.col("n_name").alias("name")).unionByName(t("region").select(F.col("r_name").alias("name"), F.col("r_regionkey").alias("k")))


@op("window_gap_lengths", "SELECT l_suppkey, max(after - l_partkey - 1) AS longest, sum(after - l_partkey - 1) AS total FROM (SELECT l_suppkey, l_partkey, lead(l_partkey) OVER (PARTITION BY l_suppkey ORDER BY l_partkey) AS after FROM (SELECT DISTINCT l_suppkey, l_partkey FROM lineitem)) GROUP BY 1")
def _(t):
    w = Window.partitionBy("l_suppkey").orderBy("l_partkey")
    gaps = t("lineitem").select("l_suppkey", "l_partkey").distinct().withColumn("gap", F.lead("l_partkey").over(w) - F.col("l_partkey") - 1)
    return gaps.groupBy("l_suppkey").agg(F.max("gap").alias("longest"), F.sum("gap").alias("total"))


@op("set_intersect_all", "SELECT CAST(l_suppkey AS BIGINT) AS k FROM lineitem INTERSECT ALL SELECT CAST(s_nationkey AS BIGINT) FROM supplier")
def _(t):
    return t("lineitem").select(F.col("l_suppkey").cast("bigint").alias("k")).intersectAll(t("supplier").select(F.col("s_nationkey").cast("bigint")))


@op("set_intersect", "SELECT l_quantity AS q FROM lineitem INTERSECT SELECT CAST(p_size AS DOUBLE) FROM part")
def _(t):
    return t("lineitem").select(F.col("l_quantity").alias("q")).intersect(t("part").select(F.col("p_size").cast("double")))


@op("set_except", "SELECT c_custkey AS k FROM customer EXCEPT SELECT o_custkey FROM orders")
def _(t):
    return t("customer").select(F.col("c_custkey").alias("k")).subtract(t("orders").select("o_custkey"))


@op("set_except_all", "SELECT l_quantity AS q FROM lineitem WHERE l_suppkey = 1 EXCEPT ALL SELECT l_quantity FROM lineitem WHERE l_suppkey = 2")
def _(t):
    q = lambda k: t("lineitem").where(F.col("l_suppkey") == k).select(F.col("l_quantity").alias("q"))
    return q(1).exceptAll(q(2))


@op("scalar_bits", "SELECT DISTINCT l_partkey AS k, l_partkey & 21 AS a, l_partkey | 8 AS o, xor(l_partkey, 5) AS x, CAST(bit_count(l_partkey) AS INTEGER) AS ones, l_partkey >> 2 AS r, l_partkey & -l_partkey AS low, bin(l_partkey) AS digits FROM lineitem")
def _(t):
    k = F.col("l_partkey")
    return t("lineitem").select(k.alias("k"), k.bitwiseAND(F.lit(21)).alias("a"), k.bitwiseOR(F.lit(8)).alias("o"), k.bitwiseXOR(F.lit(5)).alias("x"), F.bit_count(k).alias("ones"), F.shiftright(k, 2).alias("r"), k.bitwiseAND(-k).alias("low"), F.bin(k).alias("digits")).distinct()


@op("scalar_strings", "SELECT p_partkey, upper(substring(p_name, 1, 3)) AS s, length(p_name) AS n, split_part(p_name, ' ', 2) AS second, regexp_extract(p_brand, '([0-9]+)', 1) AS number, p_type || '-' || p_size AS both_of FROM part")
def _(t):
    return t("part").select("p_partkey", F.upper(F.substring("p_name", 1, 3)).alias("s"), F.length("p_name").cast("bigint").alias("n"), F.split_part("p_name", F.lit(" "), F.lit(2)).alias("second"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("number"), F.concat_ws("-", "p_type", F.col("p_size").cast("string")).alias("both_of"))


@op("scalar_dates", "SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS month, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days, CAST(CAST(o_orderdate AS DATE) + INTERVAL 1 MONTH AS DATE) AS later FROM orders")
def _(t):
    d = F.to_date("o_orderdate")
    return t("orders").select("o_orderkey", F.trunc(d, "month").alias("month"), F.year(d).alias("y"), F.datediff(d, F.lit("1995-01-01").cast("date")).alias("days"), F.add_months(d, 1).alias("later"))


@op("scalar_math", "SELECT s_suppkey, CAST(floor(s_acctbal) AS BIGINT) AS f, round(abs(s_acctbal), 1) AS a, round(sqrt(abs(s_acctbal)), 4) AS root, round(log2(abs(s_acctbal) + 1), 6) AS l FROM supplier")
def _(t):
    b = F.col("s_acctbal")
    return t("supplier").select("s_suppkey", F.floor(b).alias("f"), F.round(F.abs(b), 1).alias("a"), F.round(F.sqrt(F.abs(b)), 4).alias("root"), F.round(F.log2(F.abs(b) + 1), 6).alias("l"))


@op("scalar_arrays", "SELECT vec_id, CAST(len(embedding) AS INTEGER) AS n, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings")
def _(t):
    return t("embeddings").select("vec_id", F.size("embedding").alias("n"), F.size(F.filter("embedding", lambda x: x > 0)).cast("bigint").alias("positive"))


@op("scalar_explode", "SELECT x AS word, count(*) AS n FROM (SELECT unnest(string_split(p_name, ' ')) AS x FROM part) GROUP BY 1")
def _(t):
    return t("part").select(F.explode(F.split("p_name", " ")).alias("word")).groupBy("word").agg(_n().alias("n"))


@op("scalar_maps", "SELECT lang, count(DISTINCT source) AS sources, coalesce(count(*) FILTER (source = 'src1'), 0) AS of_src1 FROM documents WHERE source IS NOT NULL GROUP BY lang")
def _(t):
    """Counts by source gathered in a map for each language."""
    each = t("documents").where("source is not null").groupBy("lang", "source").agg(_n().alias("n"))
    held = each.groupBy("lang").agg(F.map_from_entries(F.collect_list(F.struct("source", "n"))).alias("m"))
    return held.select("lang", F.size(F.map_keys("m")).cast("bigint").alias("sources"), F.coalesce(F.element_at("m", F.lit("src1")), F.lit(0)).alias("of_src1"))


@op("scalar_json", "SELECT CAST(json_extract(props, '$.k') AS INTEGER) AS k, count(*) AS n FROM events GROUP BY 1")
def _(t):
    return t("events").select(F.from_json("props", "k int")["k"].alias("k")).groupBy("k").agg(_n().alias("n"))


@op("scalar_case_cast", "SELECT doc_id, CASE WHEN n_chars > 2000 THEN 'long' WHEN n_chars > 500 THEN 'middle' ELSE 'short' END AS kind, nullif(lang, 'en') AS other, coalesce(nullif(lang, 'en'), '-') AS filled FROM documents")
def _(t):
    return t("documents").select("doc_id", F.when(F.col("n_chars") > 2000, "long").when(F.col("n_chars") > 500, "middle").otherwise("short").alias("kind"), F.nullif("lang", F.lit("en")).alias("other"), F.coalesce(F.nullif("lang", F.lit("en")), F.lit("-")).alias("filled"))


@op("scalar_decimals", "SELECT l_returnflag, CAST(sum(CAST(l_extendedprice AS DECIMAL(15,2))) AS DOUBLE) AS total FROM lineitem GROUP BY 1")
def _(t):
    return t("lineitem").groupBy("l_returnflag").agg(F.sum(F.col("l_extendedprice").cast("decimal(15,2)")).cast("double").alias("total"))
