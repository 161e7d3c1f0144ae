"""The experiment workloads on the given tables: stores, searches with fixed seeds, and their SQL.

Filter values are drawn from the attributes' domains by a seeded generator that needs no table, so that
the same values stand in the Spark query and in the SQL.
"""

from __future__ import annotations

import datetime as dt
import random
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from keyhop.functions.curve import KeyLayout
from keyhop.plans.filters import Between, Eq, Filter, In
from keyhop.runtime import Scratch
from keyhop.sources.facts import FACTS, KINDS, STAR_SQL, codecs, fact
from keyhop.sources.store import KeyedStore

_STORES: dict[tuple, KeyedStore] = {}
DAY0 = dt.date(1995, 1, 1)
#: Domains at every scale factor: values that exist in any of the tables.
DOMAINS = {
    "l_partkey": (1, 200), "o_custkey": (1, 150), "l_suppkey": (1, 10), "p_size": (1, 50), "l_quantity": (1, 50), "c_nationkey": (0, 24), "s_nationkey": (0, 24), "l_shipdate": (0, 2400), "o_orderdate": (0, 2400), "l_discount": (0, 10), "l_tax": (0, 8),
}
#: The tables' string domains, in order.
STRINGS = {
    "p_brand": sorted(f"Brand#{i}" for i in range(1, 26)),
    "p_type": ["ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD"],
    "c_mktsegment": ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"],
    "o_orderpriority": ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"],
    "o_orderstatus": ["F", "O", "P"],
    "l_returnflag": ["A", "N", "R"],
    "l_linestatus": ["F", "O"],
}


@dataclass(frozen=True)
class Workload:
    """A named search over a fact table."""

    name: str
    fact: str
    filters: dict[str, Filter]

    @property
    def sql(self) -> str:
        return f"SELECT count(*) AS count FROM ({fact_sql(self.fact)}) f WHERE {where_sql(self.filters)}"


def fact_sql(name: str) -> str:
    return "SELECT * FROM lineitem" if name == "fact5" else STAR_SQL


def literal(name: str, v) -> str:
    if isinstance(v, dt.date):
        return f"DATE '{v}'"
    return f"'{v}'" if isinstance(v, str) else repr(v)


def column_sql(name: str) -> str:
    if KINDS.get(name) == "days":
        return f"CAST({name} AS DATE)"
    return f"round({name}, 2)" if KINDS.get(name) == "cents" else name


def filter_sql(name: str, f: Filter) -> str:
    c = column_sql(name)
    if isinstance(f, Eq):
        return f"{c} = {literal(name, f.value)}"
    if isinstance(f, In):
        return f"{c} IN ({', '.join(literal(name, v) for v in f.values)})"
    if isinstance(f, Between):
        return " AND ".join(x for x in ((f"{c} >= {literal(name, f.lo)}" if f.lo is not None else ""), (f"{c} <= {literal(name, f.hi)}" if f.hi is not None else "")) if x)
    raise ValueError(type(f))


def where_sql(filters: dict[str, Filter]) -> str:
    return " AND ".join(f"({filter_sql(n, f)})" for n, f in filters.items()) or "TRUE"


def draw(rng: random.Random, name: str, kind: str) -> Filter:
    """A filter of kind P (point), R (range) or S (set) with values from the domain."""
    if KINDS[name] == "dict":
        values = STRINGS[name]
        if kind == "P":
            return Eq(rng.choice(values))
        if kind == "S":
            return In(tuple(sorted(rng.sample(values, min(len(values), rng.randint(2, 4))))))
        a, b = sorted((rng.choice(values), rng.choice(values)))
        return Between(a, b)
    lo, hi = DOMAINS[name]

    def value(x: int):
        if KINDS[name] == "days":
            return DAY0 + dt.timedelta(days=x)
        return round(x / 100, 2) if KINDS[name] == "cents" else float(x) if name == "l_quantity" else x

    if kind == "P":
        return Eq(value(rng.randint(lo, hi)))
    if kind == "S":
        return In(tuple(value(x) for x in sorted(rng.sample(range(lo, hi + 1), min(4, hi - lo + 1)))))
    width = max(1, (hi - lo) // rng.choice((3, 6, 12)))
    a = rng.randint(lo, hi - width)
    return Between(value(a), value(a + width))


def mixes(fact_name: str, kinds: str, draws: int, seed: int = 42, attributes: tuple[str, ...] | None = None) -> list[Workload]:
    """``draws`` searches with the given kinds on random distinct attributes."""
    rng = random.Random(f"{seed}-{fact_name}-{kinds}")
    out = []
    for i in range(draws):
        names = rng.sample(list(attributes or FACTS[fact_name]), len(kinds))
        out.append(Workload(f"{kinds.lower()}_{i}", fact_name, {n: draw(rng, n, k) for n, k in zip(names, kinds, strict=True)}))
    return out


def single(fact_name: str, kind: str, seed: int = 42) -> list[Workload]:
    """One search of this kind for each attribute."""
    rng = random.Random(f"{seed}-{fact_name}-single-{kind}")
    return [Workload(f"{kind.lower()}1_{n}", fact_name, {n: draw(rng, n, kind)}) for n in FACTS[fact_name]]


def points(fact_name: str, most: int = 5, draws: int = 4, seed: int = 42) -> list[Workload]:
    """Single and multiple points on random attributes."""
    return [w for k in range(1, most + 1) for w in mixes(fact_name, "P" * k, draws, seed)]


def contest() -> list[Workload]:
    """Sixteen queries with points and ranges on the widest fact table."""
    day = lambda x: DAY0 + dt.timedelta(days=x)
    f = [
        {"l_shipdate": Eq(day(700))},
        {"l_shipdate": Between(day(730), day(760))},
        {"l_partkey": Eq(77)},
        {"o_custkey": Between(20, 27)},
        {"l_suppkey": Eq(4), "l_returnflag": Eq("R")},
        {"c_nationkey": Eq(7), "o_orderdate": Between(day(365), day(729))},
        {"p_brand": Eq(STRINGS["p_brand"][12]), "p_size": Between(10, 20)},
        {"l_quantity": Between(10.0, 20.0), "l_discount": Between(0.02, 0.05), "l_shipdate": Between(day(365), day(729))},
        {"o_orderpriority": Eq(STRINGS["o_orderpriority"][0]), "l_linestatus": Eq("F")},
        {"s_nationkey": Eq(3), "c_nationkey": Eq(8)},
        {"p_type": Eq(STRINGS["p_type"][1]), "c_mktsegment": Eq(STRINGS["c_mktsegment"][2]), "o_orderstatus": Eq("O")},
        {"l_tax": Between(0.01, 0.04), "l_discount": Eq(0.05)},
        {"o_custkey": Eq(55), "l_shipdate": Between(day(100), day(1500))},
        {"l_partkey": Between(20, 60), "l_suppkey": Between(2, 5)},
        {"o_orderstatus": Eq("F"), "l_returnflag": Eq("A"), "l_linestatus": Eq("O"), "c_mktsegment": Eq(STRINGS["c_mktsegment"][0]), "o_orderpriority": Eq(STRINGS["o_orderpriority"][1])},
        {"l_linestatus": Eq("O")},
    ]
    return [Workload(f"q{i + 1:02d}", "fact18", x) for i, x in enumerate(f)]


def store(spark: SparkSession, sf_dir: str, name: str, slices: int = 32, layout: str = "interleave", aligned: bool = False, row_group_rows: int | None = None, keys_only: bool = False) -> KeyedStore:
    """The fact table's store, built once for each session, table and shape."""
    key = (spark.sparkContext.applicationId, sf_dir, name, slices, layout, aligned, row_group_rows, keys_only)
    if key not in _STORES:
        df = fact(spark, sf_dir, name)
        _STORES[key] = KeyedStore.build(df, layout_of(df, name, layout), Scratch(spark, f"store-{name}").root, slices, aligned, row_group_rows, kept=[] if keys_only else None)
    return _STORES[key]


def layout_of(df: DataFrame, name: str, kind: str) -> KeyLayout:
    """A layout by name: interleave, junior, odometer, blocked2, blocked4, or last:<attribute> (an odometer that ends with it)."""
    attributes = codecs(df, FACTS[name])
    if kind == "junior":
        return KeyLayout.interleave(attributes, "junior")
    if kind == "odometer":
        return KeyLayout.odometer(attributes)
    if kind.startswith("blocked"):
        return KeyLayout.blocked(attributes, int(kind[7:]))
    if kind.startswith("last:"):
        last = [a for a in attributes if a.name == kind[5:]]
        return KeyLayout.odometer([a for a in attributes if a not in last] + last)
    return KeyLayout.interleave(attributes)
