"""Measuring the scan-to-seek ratio at two granularities: rows of a cursor, and slices of a store."""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from keyhop.sources.store import KeyedStore


def row_ratio(store: KeyedStore, seeks: int = 200) -> float:
    """Cost of a step to the next row over cost of a seek, timed in the executors over all keys of all slices.

    In each batch every key is tested against a pattern, and ``seeks`` random keys of it are sought.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rng = np.random.default_rng(1)
        for batch in batches:
            keys = batch.column(0).to_numpy()
            if not len(keys):
                continue
            targets = rng.choice(keys, seeks)
            start = time.perf_counter()
            np.flatnonzero((keys & keys[0]) == keys[0])
            middle = time.perf_counter()
            for t in targets:
                np.searchsorted(keys, t)
            end = time.perf_counter()
            yield pa.RecordBatch.from_arrays([pa.array([len(keys)], pa.int64()), pa.array([middle - start]), pa.array([seeks], pa.int64()), pa.array([end - middle])], ["rows", "scan", "seeks", "seek"])

    timed_rows = store.data.select(store.layout.key_columns[0]).mapInArrow(run, "rows bigint, scan double, seeks bigint, seek double")
    got = timed_rows.agg(*(F.sum(c).alias(c) for c in ("rows", "scan", "seeks", "seek"))).first()
    return (got["scan"] / got["rows"]) / (got["seek"] / got["seeks"]) if got["rows"] else 1.0


def slice_ratio(store: KeyedStore, reads: int = 6) -> float:
    """Cost of one row over cost of one more slice, from a least-squares fit of read times.

    Keys are read into an exclusive or: their sum leaves the range of a long where keys are long or rows many.
    """
    sizes = [(r["slice"], r["rows"]) for r in store.catalog.orderBy("slice").collect()]
    facts = []
    for i in range(1, reads + 1):
        ids = [s for s, _ in sizes[: max(1, len(sizes) * i // reads)]]
        rows = sum(n for s, n in sizes if s in set(ids))
        start = time.perf_counter()
        store.data.where(F.col("slice").isin(ids)).agg(F.bit_xor("k0")).collect()
        facts.append((rows, len(ids), 1.0, time.perf_counter() - start))
    a = np.array(facts)
    weights, *_ = np.linalg.lstsq(a[:, :3], a[:, 3], rcond=None)
    per_row, per_slice = max(weights[0], 1e-9), max(weights[1], 1e-6)
    return float(per_row / per_slice)


def calibrate(store: KeyedStore) -> dict[str, float]:
    """The ratio by granularity: of rows within a batch, and of slices."""
    return {"row": row_ratio(store), "slice": slice_ratio(store)}


def timed(action, runs: int = 10) -> float:
    """Mean seconds of ``runs`` calls without the fastest and the slowest."""
    times = []
    for _ in range(runs):
        start = time.perf_counter()
        action()
        times.append(time.perf_counter() - start)
    times.sort()
    kept = times[1:-1] if len(times) > 2 else times
    return sum(kept) / len(kept)


def calibrate_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    from keyhop.workload import store

    return spark.createDataFrame([(k, float(v)) for k, v in calibrate(store(spark, sf_dir, "fact5")).items()], "granularity string, ratio double")
