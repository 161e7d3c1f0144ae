"""Packing token sequences by exact complements, then best fit.

The planner needs only how many pieces there are of each length: at most ``capacity`` numbers, whatever
the size of the corpus. It fills gaps exactly with one, two or three lengths whose sum is the gap,
consuming each combination as often as the counts allow, and lays out what is left by best fit. The
result is a table of intervals (length, from, to) -> (first sequence, offset), and each piece finds its
place by its number among the pieces of its length. That numbering is distributed: pieces are numbered
within their task, and a prefix sum over tasks of the per-task histograms gives each task its start.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from keyhop.llm import bpe
from keyhop.runtime import Scratch, ship

END_ID = 1


class Plan:
    """Groups of equal sequences: (how many, lengths in order)."""

    def __init__(self, counts: np.ndarray, capacity: int):
        self.capacity = capacity
        self.left = counts.astype(np.int64).copy()
        self.groups: list[tuple[int, tuple[int, ...]]] = []
        self._exact()
        self._best_fit()

    def _take(self, lengths: tuple[int, ...]) -> bool:
        """Consume one combination as often as the counts allow."""
        need: dict[int, int] = {}
        for x in lengths:
            need[x] = need.get(x, 0) + 1
        times = min(int(self.left[x]) // k for x, k in need.items())
        if times <= 0:
            return False
        for x, k in need.items():
            self.left[x] -= times * k
        self.groups.append((times, lengths))
        return True

    def _pair(self, total: int) -> tuple[int, int] | None:
        """The available pair of lengths with this sum of which there is most."""
        if total < 2:
            return None
        half = total // 2
        low = self.left[1 : half + 1]
        high = self.left[total - 1 : total - half - 1 : -1]
        both = np.minimum(low, high)
        if total % 2 == 0:
            both[-1] = self.left[half] // 2
        best = int(both.argmax())
        return (best + 1, total - best - 1) if both[best] > 0 else None

    def _exact(self) -> None:
        c = self.capacity
        if self.left[c]:
            self._take((c,))
        for a in range(c - 1, 0, -1):
            while self.left[a]:
                gap = c - a
                if gap <= c and self.left[gap] and self._take((a, gap)):
                    continue
                if (pair := self._pair(gap)) and self._take((a, *pair)):
                    continue
                if not self._triple(a, gap):
                    break

    def _triple(self, a: int, gap: int) -> bool:
        for z in (np.flatnonzero(self.left[1 : gap - 1])[::-1] + 1).tolist() if gap > 2 else ():
            if z * 3 < gap:  # z is the largest of the three
                break
            if (pair := self._pair(gap - z)) and self._take((a, z, *pair)):
                return True
        return False

    def _best_fit(self) -> None:
        bins: dict[int, list[tuple[int, tuple[int, ...]]]] = {}
        gaps = np.zeros(self.capacity + 1, np.int64)
        for x in (np.flatnonzero(self.left)[::-1]).tolist():
            n = int(self.left[x])
            while n:
                fit = np.flatnonzero(gaps[x:])
                gap = x + int(fit[0]) if len(fit) else self.capacity
                have, lengths = bins[gap].pop() if len(fit) else (n, ())
                each = min(gap // x, n)
                used = min(have, n // each)
                if len(fit):
                    gaps[gap] -= have
                    if have > used:
                        bins[gap].append((have - used, lengths))
                        gaps[gap] += have - used
                n -= used * each
                rest = gap - each * x
                bins.setdefault(rest, []).append((used, lengths + (x,) * each))
                gaps[rest] += used
        self.left[:] = 0
        self.groups += [g for held in bins.values() for g in held]

    @property
    def sequences(self) -> int:
        return sum(m for m, _ in self.groups)

    def intervals(self) -> dict[str, np.ndarray]:
        """For each length and range of numbers: the first sequence and the offset, ordered by (length, from)."""
        cursor: dict[int, int] = {}
        rows, base = [], 0
        for times, lengths in self.groups:
            offset = 0
            for x in lengths:
                start = cursor.get(x, 0)
                cursor[x] = start + times
                rows.append((x, start, base, offset))
                offset += x
            base += times
        rows.sort()
        cols = np.array(rows, np.int64).reshape(-1, 4).T
        return dict(zip(("length", "start", "sequence", "offset"), cols, strict=True))


def _pieces(rows: DataFrame, tokenizer_path: str, capacity: int, id_type: str, with_ids: bool) -> DataFrame:
    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = bpe.worker_ids(tokenizer_path).encode
        end, step, task = bpe.little_endian([END_ID]), 4 * capacity, TaskContext.get().partitionId()
        seen: dict[int, int] = {}
        for batch in batches:
            ids = batch.column(0)
            at, number, start, length, crc, rank, raw = [], [], [], [], [], [], []
            for i, text in enumerate(batch.column(1)):
                tokens = encode(text.as_py()) + end
                for k, pos in enumerate(range(0, len(tokens), step)):
                    part = tokens[pos : pos + step]
                    n = len(part) // 4
                    at.append(i)
                    number.append(k)
                    start.append(pos // 4)
                    length.append(n)
                    crc.append(zlib.crc32(part))
                    seen[n] = (r := seen.get(n, 0)) + 1
                    rank.append(r)
                    if with_ids:
                        raw.append(part)
            arrays = [ids.take(pa.array(at, pa.int64())), pa.array(number, pa.int32()), *(pa.array(x, pa.int64()) for x in (start, length, crc)), pa.array([task] * len(at), pa.int32()), pa.array(rank, pa.int64())]
            names = ["id", "piece", "start", "length", "ids_crc32", "task", "rank"]
            if with_ids:
                arrays.append(pa.array(raw, pa.binary()))
                names.append("ids")
            yield pa.RecordBatch.from_arrays(arrays, names)

    kind = f"id {id_type}, piece int, start bigint, length bigint, ids_crc32 bigint, task int, rank bigint" + ", ids binary" * with_ids
    return rows.mapInArrow(cut, kind)


def pack(df: DataFrame, tokenizer_path: str, capacity: int = 4096, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """A row for each piece: its id, ``piece``, ``start``, ``length``, ``ids_crc32``, ``sequence_id``, ``offset``.

    Every row of ``df`` is one document (equal ids stay apart); a null text is an empty one, which still
    holds the end token. Only documents of more than ``capacity`` tokens are cut. ``with_ids`` adds the
    piece's ids as little-endian bytes. Other columns are not read. An empty table gives no rows.
    """
    spark = df.sparkSession
    ship(spark)
    id_type = df.schema[id_col].dataType.simpleString()
    rows = df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    pieces = Scratch(spark, "packing").save(_pieces(rows, tokenizer_path, capacity, id_type, with_ids), "pieces")
    per_task = pieces.groupBy("task", "length").agg((F.max("rank") + 1).alias("n"))
    before = Window.partitionBy("length").orderBy("task").rowsBetween(Window.unboundedPreceding, -1)
    starts = per_task.select("task", "length", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("first"))
    counts = np.zeros(capacity + 1, np.int64)
    for r in per_task.groupBy("length").agg(F.sum("n").alias("n")).collect():  # at most `capacity` rows
        counts[r["length"]] = r["n"]
    plan = Plan(counts, capacity).intervals()
    shift = 40
    keys = (plan["length"] << shift) + plan["start"]

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            length, number = batch.column("length").to_numpy(), batch.column("number").to_numpy()
            found = np.searchsorted(keys, (length << shift) + number, side="right") - 1
            sequence = plan["sequence"][found] + number - plan["start"][found]
            kept = [batch.column(n) for n in names]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(sequence, pa.int64()), pa.array(plan["offset"][found], pa.int64())], [*names, "sequence_id", "offset"])

    names = ["id", "piece", "start", "length", "ids_crc32", *["ids"] * with_ids]
    numbered = pieces.join(starts, ["task", "length"]).withColumn("number", F.col("rank") + F.col("first")).select(*names, "number")
    kind = f"id {id_type}, piece int, start bigint, length bigint, ids_crc32 bigint" + ", ids binary" * with_ids + ", sequence_id bigint, offset bigint"
    return numbered.mapInArrow(place, kind).withColumnRenamed("id", id_col)
