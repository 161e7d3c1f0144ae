"""The fact tables of the experiments: star joins of the given tables, and their dimensions' codecs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from keyhop.functions.curve import Attribute, Codec
from keyhop.runtime import table

#: Attribute -> how it is coded.
KINDS = {
    "l_partkey": "raw", "o_custkey": "raw", "l_shipdate": "days", "o_orderdate": "days", "l_suppkey": "raw", "p_size": "raw", "l_quantity": "raw", "c_nationkey": "raw", "s_nationkey": "raw",
    "p_brand": "dict", "p_type": "dict", "c_mktsegment": "dict", "o_orderpriority": "dict", "o_orderstatus": "dict", "l_returnflag": "dict", "l_linestatus": "dict", "l_discount": "cents", "l_tax": "cents",
    "lang": "dict", "source": "dict", "quality": "raw", "toxic": "raw", "n_chars": "bins",
    "user_id": "raw", "event_type": "dict", "day": "days", "hour": "raw", "value": "bins",
}

FACTS = {
    "fact5": ("l_partkey", "l_shipdate", "l_suppkey", "l_quantity", "l_discount"),
    "fact10": ("l_shipdate", "o_orderdate", "l_suppkey", "l_quantity", "c_nationkey", "l_discount", "o_orderpriority", "o_orderstatus", "l_returnflag", "l_linestatus"),
    "fact16": ("l_partkey", "o_custkey", "l_shipdate", "o_orderdate", "l_suppkey", "p_size", "l_quantity", "c_nationkey", "s_nationkey", "p_brand", "p_type", "c_mktsegment", "o_orderpriority", "o_orderstatus", "l_returnflag", "l_linestatus"),
    "fact18": ("l_partkey", "o_custkey", "l_shipdate", "o_orderdate", "l_suppkey", "p_size", "l_quantity", "c_nationkey", "s_nationkey", "p_brand", "p_type", "c_mktsegment", "o_orderpriority", "o_orderstatus", "l_returnflag", "l_linestatus", "l_discount", "l_tax"),
    "doc5": ("n_chars", "source", "lang", "quality", "toxic"),
    "ev5": ("user_id", "value", "day", "hour", "event_type"),
}

#: Dictionaries become literals of the layout, so they must be short; more values than this are refused.
LONGEST_DICTIONARY = 4096

#: The star join as SQL, for oracles and for the star baseline.
STAR_SQL = """SELECT l.*, o.o_custkey, o.o_orderdate, o.o_orderstatus, o.o_orderpriority, c.c_nationkey, c.c_mktsegment, p.p_size, p.p_brand, p.p_type, s.s_nationkey
FROM lineitem l JOIN orders o ON l.l_orderkey = o.o_orderkey JOIN customer c ON o.o_custkey = c.c_custkey JOIN part p ON l.l_partkey = p.p_partkey JOIN supplier s ON l.l_suppkey = s.s_suppkey"""


def star(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem with its orders', customers', parts' and suppliers' attributes; Spark picks the joins by size."""
    t = lambda n: table(spark, sf_dir, n)
    return (
        t("lineitem")
        .join(t("orders").select("o_orderkey", "o_custkey", "o_orderdate", "o_orderstatus", "o_orderpriority"), F.col("l_orderkey") == F.col("o_orderkey"))
        .join(t("customer").select("c_custkey", "c_nationkey", "c_mktsegment"), F.col("o_custkey") == F.col("c_custkey"))
        .join(t("part").select("p_partkey", "p_size", "p_brand", "p_type"), F.col("l_partkey") == F.col("p_partkey"))
        .join(t("supplier").select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    )


def fact(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The dimensions of a fact table, and its measure where it has one."""
    dims = FACTS[name]
    if name == "fact5":
        return table(spark, sf_dir, "lineitem").select(*dims, "l_extendedprice")
    if name == "doc5":
        docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
        return docs.join(labels, "doc_id", "left").select("doc_id", *dims)
    if name == "ev5":
        return events(table(spark, sf_dir, "events")).select("event_id", *dims)
    return star(spark, sf_dir).select(*dims, "l_extendedprice")


def events(df: DataFrame) -> DataFrame:
    """Events with ``day`` and ``hour``."""
    return df.withColumns({"day": F.to_date("ts"), "hour": F.hour("ts")})


def codecs(df: DataFrame, names: tuple[str, ...], bins: int = 64) -> list[Attribute]:
    """Attributes with widths from the data: one aggregation for all numeric ones, one distinct for each small dictionary."""
    number = lambda c: F.to_date(c) if KINDS[c] == "days" else F.col(c)
    plain = [c for c in names if KINDS[c] != "dict"]
    ends = df.agg(*(F.min(number(c)).alias(f"lo_{c}") for c in plain), *(F.max(number(c)).alias(f"hi_{c}") for c in plain), *(F.slice(F.array_sort(F.collect_set(c)), 1, LONGEST_DICTIONARY + 1).alias(f"d_{c}") for c in names if KINDS[c] == "dict")).first()
    out = []
    for c in names:
        kind = KINDS[c]
        if kind == "dict":
            values = tuple(ends[f"d_{c}"])
            if len(values) > LONGEST_DICTIONARY:
                raise ValueError(f"{c} has more than {LONGEST_DICTIONARY} values: number them by functions.dictionary and a join")
            out.append(Attribute(c, Codec("dict", values=values, size=len(values))))
            continue
        lo, hi = ends[f"lo_{c}"], ends[f"hi_{c}"]
        if lo is None:
            out.append(Attribute(c, Codec("raw", 0, size=1)))
        elif kind == "days":
            out.append(Attribute(c, Codec("days", lo.toordinal(), size=hi.toordinal() - lo.toordinal() + 1)))
        elif kind == "cents":
            out.append(Attribute(c, Codec("raw", lo, 0.01, size=round((hi - lo) / 0.01) + 1)))
        elif kind == "bins":
            out.append(Attribute(c, Codec("bins", float(lo), max((float(hi) - float(lo)) / bins, 1e-9), size=bins)))
        else:
            out.append(Attribute(c, Codec("raw", int(lo), size=int(hi) - int(lo) + 1)))
    return out
