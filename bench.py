"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

Stores are built first and timed apart; each query then runs after one warm-up, and the best of three
runs counts. Beside that: the contest of 16 queries (best of ten runs; total and maximum) against the
star join in Spark and against DuckDB on the same files, and the strategies on the five-attribute store
(mean of ten runs without the fastest and the slowest).
"""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

HEADLINE = (
    "base_fullscan_star", "base_fullscan", "count_p1_l_partkey", "count_p1_p_brand", "count_r1_l_shipdate", "count_s1_l_suppkey", "count_pp_0", "count_ppp_0", "count_prs_0", "count_fact10_ppp_0", "count_fact5_pp_0", "hybrid_sliced_mixed",
    *(f"contest_q{i:02d}" for i in range(1, 17)),
)


def best(action, runs: int) -> float:
    """The fastest of several runs after one that doesn't count."""
    action()
    times = []
    for _ in range(runs):
        start = time.perf_counter()
        action()
        times.append(time.perf_counter() - start)
    return min(times)


def contest(spark: SparkSession, sf_dir: str, every: dict, cpus: int) -> dict:
    """Total and maximum over the contest's queries: the keyed store, the star join of the same tables, and DuckDB on that join."""
    import duckdb

    from keyhop import queries as engine
    from keyhop import workload as wl
    from keyhop.plans.filters import condition
    from keyhop.sources.facts import fact

    duck = duckdb.connect(config={"threads": cpus})
    for t in ("lineitem", "orders", "customer", "part", "supplier"):
        duck.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    sql, layout = engine.oracle_sql(), wl.store(spark, sf_dir, "fact18").layout
    seconds = {"store": [], "star_join": [], "duckdb": []}
    for w in wl.contest():
        seconds["store"].append(best(lambda: every[f"contest_{w.name}"](spark, sf_dir).collect(), 10))
        seconds["star_join"].append(best(lambda: fact(spark, sf_dir, "fact18").where(condition(layout, w.filters)).count(), 2))
        seconds["duckdb"].append(best(lambda: duck.sql(sql[f"contest_{w.name}"]).fetchall(), 10))
    return {k: {"total": round(sum(v), 3), "max": round(max(v), 3)} for k, v in seconds.items()}


def strategies(spark: SparkSession, sf_dir: str, every: dict) -> dict:
    """Seconds of counts by strategy: which slices are read, and, over all rows, the executions with their counters."""
    from keyhop import workload as wl
    from keyhop.calibrate import timed
    from keyhop.queries import MIXED

    store, out = wl.store(spark, sf_dir, "fact5"), {}
    for kind, filters in MIXED.items():
        for strategy in ("crawl", "leap", "hybrid"):
            store.count_where(strategy, 1e-4, **filters).collect()
            out[f"slices_{strategy}_{kind}"] = round(timed(lambda: store.count_where(strategy, 1e-4, **filters).collect()), 4)
    for strategy in ("crawl", "leap", "hybrid"):
        every[f"{strategy}_point"](spark, sf_dir).collect()
        out[f"rows_{strategy}_point"] = round(timed(lambda: every[f"{strategy}_point"](spark, sf_dir).collect(), 5), 4)
    return out


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = SparkSession.builder.master(f"local[{cpus}]").appName("keyhop-bench").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "8g").config("spark.sql.shuffle.partitions", cpus).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    from keyhop import queries as engine
    from keyhop import workload as wl
    from keyhop.operators.race import point_counters
    from keyhop.plans import costs
    from keyhop.plans.filters import Eq

    builds = {}
    for name in ("fact5", "fact10", "fact16", "fact18"):
        start = time.perf_counter()
        wl.store(spark, sf_dir, name)
        builds[name] = round(time.perf_counter() - start, 3)
    every = engine.queries()
    times = {}
    for name in HEADLINE:
        times[name] = round(best(lambda: every[name](spark, sf_dir).collect(), 3), 4)
    # Costs of the strategies in seeks (scan-to-seek ratio 0.5), per attribute of the five-attribute table.
    store = wl.store(spark, sf_dir, "fact5")
    ratios = {}
    for attribute, value in (("l_partkey", 77), ("l_suppkey", 4), ("l_quantity", 17.0), ("l_discount", 0.05)):
        search = store.search(**{attribute: Eq(value)})
        n, t = store.layout.n, costs.choose_threshold(search, store.rows, 0.5).threshold
        got = {r["threshold"]: r["scans"] * 0.5 + r["jumps"] for r in point_counters(store.data, search, sorted({0, t, n})).collect()}
        ratios[attribute] = {"leap_over_crawl": round(got[0] / got[n], 4), "hybrid_over_crawl": round(got[t] / got[n], 4), "threshold": t, "n": n}
    print(json.dumps({"contest": contest(spark, sf_dir, every, int(cpus)), "strategy_seconds": strategies(spark, sf_dir, every), "metric": "total seconds of headline queries", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": sf_dir, "build_sec": builds, "strategy_costs": ratios}))
    spark.stop()


if __name__ == "__main__":
    main()
