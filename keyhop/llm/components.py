"""Connected components of a graph given as edges, by random-mate contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyhop.runtime import Scratch


def components(edges: DataFrame, scratch: Scratch, label: str) -> DataFrame:
    """``node`` and ``component`` (the smallest node reachable) for every node of ``edges`` (columns ``a``, ``b``).

    In each round every node joins the neighbour with the smallest priority, if that is smaller than its
    own, and edges are rewritten to the nodes joined. The first round's priority is the node itself,
    which ends stars around their smallest node at once; later ones are pseudo-random, so that the
    number of edges falls by a constant factor in expectation, on chains as on stars. Each round is an aggregation and joins of which Spark
    can split a skewed side; no neighbour list is gathered anywhere. Round results are written tables.
    """
    edges = scratch.save(edges.where(F.col("a") != F.col("b")).select("a", "b").distinct(), f"{label}-edges0")
    steps: list[DataFrame] = []
    while not edges.isEmpty():
        k = len(steps)
        rank = lambda c: F.xxhash64(F.lit(f"round{k}"), F.col(c)) if k else F.lit(0).cast("bigint")  # noqa: B023, E731
        both = edges.union(edges.select("b", "a"))
        best = both.groupBy("a").agg(F.min(F.struct(rank("b").alias("rank"), F.col("b").alias("to"))).alias("best"))
        own = F.struct(rank("a").alias("rank"), F.col("a").alias("to"))
        step = scratch.save(best.select(F.col("a").alias("from"), F.least(F.col("best"), own)["to"].alias("to")), f"{label}-step{k}")
        steps.append(step)
        one = edges.join(step, F.col("a") == F.col("from")).select(F.col("to").alias("a"), "b")
        two = one.join(step, F.col("b") == F.col("from")).select("a", F.col("to").alias("b"))
        edges = scratch.save(two.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), f"{label}-edges{k + 1}")
    if not steps:
        return edges.select(F.col("a").alias("node"), F.col("b").alias("component"))
    joined = steps[0]
    for step in steps[1:]:
        nxt = step.withColumnsRenamed({"from": "mid", "to": "last"})
        joined = joined.join(nxt, F.col("to") == F.col("mid"), "left").select("from", F.coalesce("last", "to").alias("to"))
    joined = scratch.save(joined, f"{label}-joined")
    least = joined.groupBy("to").agg(F.min("from").alias("least"))
    # The node that all joined is a node of the component itself, so the smallest "from" is the smallest node.
    return joined.join(least, "to").select(F.col("from").alias("node"), F.col("least").alias("component"))
