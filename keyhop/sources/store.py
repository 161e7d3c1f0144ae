"""The keyed store: rows in key order in slices, and a catalog of the slices' key ranges.

No index beyond each slice's least and greatest key. A slice [lo, hi] can hold a match only if the next
match of lo is at most hi, which prunes for any mix of filters on any attributes. Slices that the search
takes whole need no test of their rows, and are counted from the catalog.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from keyhop.functions.bits import LIMB, joined, ones
from keyhop.functions.curve import KeyLayout
from keyhop.plans import columns, costs
from keyhop.plans.filters import Filter, condition, search_of
from keyhop.plans.restrict import normalize, reduce_for_interval
from keyhop.plans.search import Search, crawl_intervals, normal_intervals

#: A catalog of at most so many slices is kept by the driver, which then decides on slices before a
#: query's only job; larger ones are decided on by column expressions and joined.
LISTED_SLICES = 4096
#: A point search names at most 2^5 key intervals to the scan.
REGION_BITS = 5
#: About what Parquet's default row groups of 128 MB hold.
ROW_GROUP_ROWS = 1_000_000


def slice_frame(df: DataFrame, layout: KeyLayout, slices: int, aligned: bool = False, depth: int = 12, kept: list[str] | None = None) -> DataFrame:
    """``df`` encoded, with column ``slice``, partitioned by slice and sorted by key in each.

    ``aligned=False``: slices of about equal numbers of rows by range partitioning (a row hash breaks
    ties, so that a heavy key doesn't make a heavy slice). ``aligned=True``: aligned key intervals,
    split from the senior bit on until each holds no more than its share or ``depth`` bits are used.
    ``kept`` names the columns that are stored beside the keys; all are by default.
    """
    keys = layout.key_columns
    stored = [*(c for c in (df.columns if kept is None else kept) if c not in keys), *keys]
    encoded = layout.encode(df)
    if not aligned:
        names = [*df.columns]
        tie = F.xxhash64(*names)
        parted = encoded.select(*stored, tie.alias("_tie")).repartitionByRange(slices, *keys, "_tie").drop("_tie")
        return parted.withColumn("slice", F.spark_partition_id()).sortWithinPartitions("slice", *keys)
    r = min(depth, layout.n)
    top_width = layout.n - LIMB * (layout.limb_count - 1)
    r = min(r, top_width)
    prefix = F.shiftright(F.col("k0"), top_width - r).cast("int")
    counts = {x["p"]: x["n"] for x in encoded.groupBy(prefix.alias("p")).agg(F.count(F.lit(1)).alias("n")).collect()}  # at most 2^depth rows
    target = max(1, -(-sum(counts.values()) // slices))
    leaves: list[tuple[int, int]] = []

    def grow(start: int, width: int) -> None:
        rows = sum(counts.get(p, 0) for p in range(start, start + width))
        if rows == 0:
            return
        if rows <= target or width == 1:
            leaves.append((start, start + width - 1))
            return
        grow(start, width // 2)
        grow(start + width // 2, width // 2)

    grow(0, 1 << r)
    table = [0] * (1 << r)
    for i, (a, b) in enumerate(leaves):
        for p in range(a, b + 1):
            table[p] = i
    number = F.element_at(F.array(*map(F.lit, table)), prefix + 1)
    return encoded.select(*stored).withColumn("slice", number).repartition(max(1, len(leaves)), "slice").sortWithinPartitions("slice", *keys)


def catalog_of(data: DataFrame, keys: list[str]) -> DataFrame:
    """``slice``, ``rows`` and the limbs of the least and greatest key of each slice."""
    key = F.struct(*keys)
    got = data.groupBy("slice").agg(F.count(F.lit(1)).alias("rows"), F.min(key).alias("lo"), F.max(key).alias("hi"))
    ends = [F.col(f"{side}.{k}").alias(f"{side}{i}") for side in ("lo", "hi") for i, k in enumerate(keys)]
    return got.select(F.col("slice").cast("int").alias("slice"), "rows", *ends)


@dataclass
class KeyedStore:
    """A store on disk: ``path/data`` (partitioned by slice), ``path/catalog``, ``path/layout``."""

    spark: SparkSession
    path: str
    layout: KeyLayout
    row_group_rows: int = ROW_GROUP_ROWS
    _listed: tuple | None = field(default=None, repr=False)
    _frames: dict[str, DataFrame] = field(default_factory=dict, repr=False)

    @classmethod
    def build(cls, df: DataFrame, layout: KeyLayout, path: str, slices: int = 64, aligned: bool = False, row_group_rows: int | None = None, mode: str = "overwrite", kept: list[str] | None = None) -> KeyedStore:
        """Write ``df`` in key order. The range shuffle here is the only large exchange of the system.

        ``kept`` names the columns beside the keys, all by default: without them a store answers by keys alone.
        """
        spark = df.sparkSession
        writer = slice_frame(df, layout, slices, aligned, kept=kept).write.mode(mode).partitionBy("slice")
        if row_group_rows:
            writer = writer.option("parquet.block.row.count.limit", row_group_rows)
        writer.parquet(f"{path}/data")
        spark.createDataFrame([(layout.to_json(),)], "layout string").coalesce(1).write.mode("overwrite").text(f"{path}/layout")
        out = cls(spark, path, layout, row_group_rows or ROW_GROUP_ROWS)
        out.write_catalog()
        return out

    @classmethod
    def open(cls, spark: SparkSession, path: str) -> KeyedStore:
        return cls(spark, path, KeyLayout.from_json(spark.read.text(f"{path}/layout").first()[0]))

    def _read_once(self, name: str) -> DataFrame:
        """Files are listed and the schema is read once for each store object: later queries plan at once."""
        if name not in self._frames:
            self._frames[name] = self.spark.read.parquet(f"{self.path}/{name}")
        return self._frames[name]

    @property
    def data(self) -> DataFrame:
        return self._read_once("data")

    @property
    def catalog(self) -> DataFrame:
        """``slice``, ``rows``, and the limbs of the least and greatest key."""
        return self._read_once("catalog")

    def write_catalog(self) -> None:
        """From the written keys alone; the other columns are not read."""
        catalog_of(self.data, self.layout.key_columns).coalesce(1).write.mode("overwrite").parquet(f"{self.path}/catalog")

    @property
    def rows(self) -> int:
        return self.catalog.agg(F.sum("rows")).first()[0] or 0

    def search(self, **filters: Filter) -> Search:
        return normalize(search_of(self.layout, filters))

    def classify(self, search: Search, ratio: float = 1.0) -> DataFrame:
        """The catalog with ``action`` (skip, whole, crawl), ``threshold`` and ``n_eff`` for each slice.

        All of it column expressions. ``n_eff`` is the number of key bits in which a slice's keys
        differ; its threshold comes from that, its own rows and what the search leaves to test in it.
        """
        k, n = self.layout.limb_count, search.n
        catalog = self.catalog
        if search.empty:
            return catalog.withColumns({"action": F.lit("skip"), "threshold": F.lit(n), "n_eff": F.lit(0)})
        lo, hi, names = [f"lo{i}" for i in range(k)], [F.col(f"hi{i}") for i in range(k)], [f"_next{i}" for i in range(k)]
        found = columns.with_next_match(catalog, lo, search, "_y", names).withColumn("_width", columns.width_of([F.col(x) for x in lo], hi))
        found = columns.settled(found, ["_width"])
        reached = F.col(names[0]).isNotNull() & columns.after_eq(hi, [F.col(x) for x in names])
        whole = columns.whole([F.col(x) for x in lo], F.col("_width"), search)
        found = columns.settled(found.withColumn("action", F.when(~reached, "skip").when(whole, "whole").otherwise("crawl")), ["action"])
        crawled = F.col("action") == "crawl"
        threshold = columns.threshold(F.col("rows"), F.col("_width"), search, ratio) if search.restrictions else F.lit(n)
        found = found.withColumns({"threshold": F.when(crawled, threshold).otherwise(F.lit(n)), "n_eff": F.when(F.col("action") == "skip", F.lit(0)).otherwise(F.col("_width"))})
        return found.select(*catalog.columns, "action", "threshold", "n_eff")

    def prune(self, search: Search) -> DataFrame:
        """The catalog rows of slices that can hold a match."""
        return self.classify(search).where("action <> 'skip'").select(*self.catalog.columns)

    def listed(self) -> list[tuple[int, int, int, int]] | None:
        """(slice, rows, least and greatest key) in key order, read once; None for a catalog of more than ``LISTED_SLICES`` rows."""
        if self._listed is None:
            k = self.layout.limb_count
            held = self.catalog.limit(LISTED_SLICES + 1).collect()
            rows = [(r["slice"], r["rows"], joined([r[f"lo{i}"] for i in range(k)]), joined([r[f"hi{i}"] for i in range(k)])) for r in held]
            self._listed = (sorted(rows, key=lambda r: (r[2], r[3], r[0])) if len(rows) <= LISTED_SLICES else None,)
        return self._listed[0]

    def decisions(self, search: Search, strategy: str = "leap", ratio: float = 1.0) -> list[tuple[int, int, str]] | None:
        """(slice, rows, action) of the slices to read, in key order, from the listed catalog; None if it isn't listed.

        ``crawl`` reads all slices within the search's bounds. ``leap`` reads those that can hold a match
        and counts the ``whole`` ones from the catalog. ``hybrid`` also reads ``through`` the slices
        between two of these where they hold no more than 1 / ``ratio`` rows together, ``ratio`` being
        the cost of a row over that of opening one more slice.
        """
        rows = self.listed()
        if rows is None:
            return None
        if search.empty:
            return []
        least, greatest = search.bounds()
        out: list[tuple[int, int, str]] = []
        skipped: list[tuple[int, int, str]] = []
        for number, n, lo, hi in rows:
            if hi < least or lo > greatest:
                continue
            if strategy == "crawl":
                out.append((number, n, "crawl"))
                continue
            following = search.next_match(lo)
            if following is None or following > hi:
                skipped.append((number, n, "through"))
                continue
            if strategy == "hybrid" and out and sum(m for _, m, _ in skipped) * ratio <= 1:
                out += skipped
            skipped = []
            reduced = reduce_for_interval(search, lo, hi)
            out.append((number, n, "whole" if reduced is not None and not reduced.restrictions else "crawl"))
        return out

    def _read(self, slices: DataFrame) -> DataFrame:
        """The data of the given slices, by a join that prunes partitions at run time."""
        return self.data.join(slices.select("slice"), "slice", "left_semi")

    def _numbered(self, numbers: list[int]) -> DataFrame:
        """The data of the slices with these numbers, listed in the plan."""
        return self.data.where(F.col("slice").isin(numbers)) if numbers else self.data.where(F.lit(False))

    def _in(self, searches: list[Search], strategy: str = "leap", ratio: float = 1.0) -> DataFrame:
        """The data of all slices to read for any of the searches."""
        found = [self.decisions(x, strategy, ratio) for x in searches]
        if None not in found:
            return self._numbered(sorted({number for d in found for number, _, _ in d}))
        slices = None
        for x in searches:
            kept = self.prune(x).select("slice")
            slices = kept if slices is None else slices.union(kept)
        return self._read(slices.distinct())

    def _regions(self, search: Search, strategy: str, ratio: float) -> list[tuple[int, int]]:
        """Key intervals outside of which nothing matches: the bounds, or for points the regions above the threshold.

        Gaps above the strategy's threshold are left out, as far as ``REGION_BITS`` free bits allow and
        as regions hold a row group on average, so that Parquet skips row groups that stand in a gap;
        smaller gaps are scanned.
        """
        bounds = search.bounds()
        if strategy == "crawl" or not search.point or not search.mask or self.layout.limb_count > 1 or self.listed() is None:
            return [bounds]
        total = sum(n for _, n, _, _ in self.listed())
        t = 0 if strategy == "leap" else costs.choose_threshold(search, total, ratio).threshold
        free = ones(search.n) & ~search.mask
        bits = min(REGION_BITS, (total // self.row_group_rows).bit_length())
        if not bits:
            return [bounds]
        while (free >> t).bit_count() > bits:
            t += 1
        clipped = [(max(a, bounds[0]), min(b, bounds[1])) for a, b in crawl_intervals(search, t)]
        return [(a, b) for a, b in normal_intervals(clipped)]

    def _tested(self, search: Search, filters: dict[str, Filter], strategy: str = "leap", ratio: float = 1.0) -> Column:
        """The exact condition on the columns, and the key intervals on the senior limb: both for Parquet's statistics."""
        if search.empty:
            return F.lit(False)
        near = F.lit(False)
        for lo, hi in self._regions(search, strategy, ratio):
            near = near | F.col("k0").between(self.layout.limbs(lo)[0], self.layout.limbs(hi)[0])
        return condition(self.layout, filters) & near

    @property
    def attributes(self) -> list[str]:
        """The stored columns besides keys and places."""
        return [c for c in self.data.columns if c not in (*self.layout.key_columns, "slice", "batch")]

    def where(self, columns: list[str] | None = None, strategy: str = "leap", ratio: float = 1.0, **filters: Filter) -> DataFrame:
        """The matching rows: slices by strategy, key bounds and exact conditions pushed to the scan."""
        search = self.search(**filters)
        out = self._in([search], strategy, ratio).where(self._tested(search, filters, strategy, ratio))
        return out.select(*(self.attributes if columns is None else columns))

    def count_where(self, strategy: str = "leap", ratio: float = 1.0, **filters: Filter) -> DataFrame:
        """``count`` of the matching rows in one job; slices taken whole are counted from the catalog alone."""
        search = self.search(**filters)
        if not all(self.layout.attribute(a).codec.exact for a in filters):
            return self.where([], strategy, ratio, **filters).agg(F.count(F.lit(1)).alias("count"))
        tested = self._tested(search, filters, strategy, ratio)
        found = self.decisions(search, strategy, ratio)
        if found is not None:
            whole = sum(n for _, n, action in found if action == "whole")
            read = [number for number, _, action in found if action != "whole"]
            if not read:
                return self.spark.range(1).select(F.lit(whole).cast("bigint").alias("count"))
            return self._numbered(read).where(tested).agg((F.count(F.lit(1)) + F.lit(whole)).alias("count"))
        kept = self.classify(search, ratio).where("action <> 'skip'")
        some = self._read(kept.where("action = 'crawl'")).where(tested).agg(F.count(F.lit(1)).alias("n"))
        return some.union(kept.where("action = 'whole'").agg(F.sum("rows").alias("n"))).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("count"))

    def count_any(self, *alternatives: dict[str, Filter]) -> DataFrame:
        """``count`` of the rows that satisfy any of several conjunctions, each row once."""
        any_of = F.lit(False)
        for filters in alternatives:
            any_of = any_of | condition(self.layout, filters)
        return self._in([self.search(**f) for f in alternatives]).where(any_of).agg(F.count(F.lit(1)).alias("count"))

    def count_many(self, searches: dict[str, dict[str, Filter]]) -> DataFrame:
        """Counts of several searches in one scan of the union of their slices: ``name``, ``count``."""
        rows = self._in([self.search(**f) for f in searches.values()])
        one = rows.agg(*(F.count_if(condition(self.layout, f)).alias(name) for name, f in searches.items()))
        return one.select(F.explode(F.array(*(F.struct(F.lit(n).alias("name"), F.col(n).alias("count")) for n in searches))).alias("x")).select("x.*")

    def count_shortened(self, **filters: Filter) -> DataFrame:
        """``count`` of a point search's matches, testing of each key only the junior bits in which its slice's keys differ.

        The senior bits that all keys of a slice share are known from the catalog and decide there: a
        slice that disagrees with them is skipped, one without masked bits left is counted whole.
        """
        search = self.search(**filters)
        if self.layout.limb_count > 1 or not search.point:
            raise ValueError("points on keys of one limb")
        mask, pattern = search.point
        kept = self.classify(search).where("action <> 'skip'").select("slice", "rows", "action", columns.low_ones(F.col("n_eff")).alias("low"))
        held = F.lit(mask).cast("bigint").bitwiseAND(F.col("low"))
        tested = F.col("k0").bitwiseAND(held) == F.lit(pattern).cast("bigint").bitwiseAND(held)
        some = self.data.select("slice", "k0").join(kept.where("action = 'crawl'"), "slice").where(tested).agg(F.count(F.lit(1)).alias("n"))
        return some.union(kept.where("action = 'whole'").agg(F.sum("rows").alias("n"))).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("count"))

    def shortened(self) -> DataFrame:
        """``slice``, ``rows``, and the key bits that its keys share (``prefix``) and that are left (``suffix``)."""
        k = self.layout.limb_count
        width = columns.width_of(*([F.col(f"{side}{i}") for i in range(k)] for side in ("lo", "hi")))
        return self.catalog.select("slice", "rows", (F.lit(self.layout.n) - width).alias("prefix"), width.alias("suffix"))

    def crosstab(self, a: str, b: str, **filters: Filter) -> DataFrame:
        """Rows by two attributes under filters: ``a``, ``b``, ``count``."""
        return self.where([a, b], **filters).groupBy(a, b).agg(F.count(F.lit(1)).alias("count"))

    def first(self, k: int, **filters: Filter) -> DataFrame:
        """The first ``k`` matches in key order: with a listed catalog from no more slices than whole ones make necessary."""
        search = self.search(**filters)
        found = self.decisions(search)
        if found is None:
            rows = self._in([search])
        else:
            need, numbers = k, []
            for number, n, action in found:
                numbers.append(number)
                need -= n if action == "whole" else 0
                if need <= 0:
                    break
            rows = self._numbered(numbers)
        return rows.where(self._tested(search, filters)).orderBy(*self.layout.key_columns).limit(k)

    def io_report(self, search: Search) -> DataFrame:
        """Slices and rows by action."""
        return self.classify(search).groupBy("action").agg(F.count(F.lit(1)).alias("slices"), F.sum("rows").alias("rows"))

    def io_by_strategy(self, search: Search, ratio: float = 1.0) -> DataFrame:
        """``strategy``, ``slices`` and ``rows`` that each strategy reads, and ``counted`` rows that it takes from the catalog."""
        out = []
        for strategy in ("crawl", "leap", "hybrid"):
            found = self.decisions(search, strategy, ratio)
            if found is None:
                raise ValueError(f"a catalog of more than {LISTED_SLICES} slices: use io_report")
            read = [n for _, n, action in found if action != "whole"]
            out.append((strategy, len(read), sum(read), sum(n for _, n, action in found if action == "whole")))
        return self.spark.createDataFrame(out, "strategy string, slices bigint, rows bigint, counted bigint")

    def explain(self, ratio: float = 1.0, **filters: Filter) -> dict:
        """What was decided, for people: the reduced search, thresholds, what happens to the slices."""
        search = self.search(**filters)
        c = self.rows
        decision = costs.choose_threshold(search, c, ratio)
        return {
            "n": search.n, "rows": c, "restrictions": [(r.kind, bin(r.mask), r.size) for r in search.restrictions], "bounds": None if search.empty else search.bounds(), "useful_bits": costs.useful_bits(c, ratio),
            "threshold": decision.threshold, "reason": decision.reason, "slices": {r["action"]: (r["slices"], r["rows"]) for r in self.io_report(search).collect()},
        }

    def compact(self, path: str, slices: int) -> KeyedStore:
        """A new store of the same rows in ``slices`` slices: merges the runs that appends have left."""
        return KeyedStore.build(self.data.select(*self.attributes), self.layout, path, slices)
