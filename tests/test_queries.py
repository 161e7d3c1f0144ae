import duckdb
import pytest

from keyhop import queries as engine

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
NAMES = ["crawl_point", "leap_mixed", "hybrid_set", "threshold_sweep_range", "lacuna_lengths", "cofrequency", "first_in_key_order", "stream_tumbling", "stream_session", "points_fact5", "store_variants", "shortened_keys_count", "op_agg_grouped_function", "count_p1_p_brand", "count_prs_0", "count_fact10_ppp_0", "contest_q08", "hybrid_mixed", "hybrid_cluster_end_set", "cooperative_counts", "crosstab_where", "sql_front_end", "split_values_count", "stream_keyed_store", "base_materialized_cube", "op_join_as_of", "op_window_ranks", "op_agg_cube", "op_scalar_bits", "same_bag"]


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return c


def plain(v):
    return repr(v + 0.0) if isinstance(v, float) else str(v)


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_its_sql(spark, sf, duck, name):
    df = engine.queries()[name](spark, sf)
    names = sorted(df.columns)
    rel = duck.sql(engine.oracle_sql()[name])
    columns, rows = rel.columns, rel.fetchall()
    assert sorted(columns) == names
    assert sorted(tuple(plain(r[c]) for c in names) for r in df.collect()) == sorted(tuple(plain(r[columns.index(c)]) for c in names) for r in rows)


def test_behaviour_of_the_strategies(spark, sf):
    """hybrid never costs more than crawl; leap loses on the most junior attribute, where hybrid ties."""
    for kind in ("point", "range", "set", "mixed"):
        cost = {r["strategy"]: r["cost"] for r in engine.queries()[f"race_{kind}"](spark, sf).collect()}
        assert cost["hybrid"] <= cost["crawl"]
    worst = {r["strategy"]: r["cost"] for r in engine.queries()["junior_bit_worst_case"](spark, sf).collect()}
    assert worst["leap"] > worst["crawl"] and worst["hybrid"] <= worst["crawl"] * 1.01
