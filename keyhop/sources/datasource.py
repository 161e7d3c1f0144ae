"""The keyed store as a Spark data source: ``spark.read.format("keyhop").load(path)``.

Spark hands its filters over; comparisons, IN and IS NULL on dimension columns become restrictions on
the key, the catalog is pruned with them, and each remaining slice is one input partition, read as
Arrow batches with the columns asked for. Filters that were handed over are evaluated by Spark as well.
Paths are opened by Arrow: use a file system that it knows.
"""

from __future__ import annotations

import datetime as dt
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
import pyarrow.dataset as ds
from pyarrow import fs
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, In, InputPartition, IsNotNull, IsNull, LessThan, LessThanOrEqual

from keyhop.functions.bits import joined
from keyhop.functions.curve import KeyLayout
from keyhop.plans import filters as kf
from keyhop.plans.restrict import normalize
from keyhop.plans.search import Restriction, Search, normal_intervals


def _text(folder: str) -> str:
    """The first line of the text files in a folder."""
    store, root = fs.FileSystem.from_uri(folder) if "://" in folder else (fs.LocalFileSystem(), folder)
    for info in store.get_file_info(fs.FileSelector(root)):
        if info.base_name.startswith("part-"):
            with store.open_input_stream(info.path) as f:
                if line := f.readall().decode().strip():
                    return line
    raise FileNotFoundError(folder)


@dataclass
class SlicePartition(InputPartition):
    """One slice's folder."""

    path: str
    number: int


def _as_filter(f: Filter) -> tuple[str, kf.Filter] | None:
    """The store's filter for one of Spark's, if it is on one column."""
    name = getattr(f, "attribute", (None,))[0]
    value = getattr(f, "value", None)
    if isinstance(value, dt.datetime):
        value = value.date()
    if isinstance(f, EqualTo):
        return name, kf.Eq(value)
    if isinstance(f, In):
        return name, kf.In(tuple(v.date() if isinstance(v, dt.datetime) else v for v in f.value))
    if isinstance(f, GreaterThan | GreaterThanOrEqual):
        return name, kf.Between(value, None)
    if isinstance(f, LessThan | LessThanOrEqual):
        return name, kf.Between(None, value)
    if isinstance(f, IsNull):
        return name, kf.IsNull()
    return (name, kf.NotNull()) if isinstance(f, IsNotNull) else None


class StoreReader(DataSourceReader):
    """Plans and reads the slices that can hold a match."""

    def __init__(self, path: str, schema):
        self.path, self.schema = path, schema
        self.layout = KeyLayout.from_json(_text(f"{path}/layout"))
        self.restrictions: dict[str, list[tuple[int, int]]] = {}

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:  # noqa: N802
        known = {a.name for a in self.layout.attributes}
        for f in filters:
            got = _as_filter(f)
            if got and got[0] in known:
                held = self.restrictions.get(got[0])
                new = normal_intervals(got[1].intervals(self.layout.attribute(got[0])))
                self.restrictions[got[0]] = list(new) if held is None else [(max(a, x), min(b, y)) for a, b in held for x, y in new if max(a, x) <= min(b, y)]
            yield f  # Spark tests it again: strict comparisons and bins are only approximated by slices

    def partitions(self) -> list[SlicePartition]:
        search = normalize(Search(self.layout.n, tuple(Restriction(self.layout.mask(k), tuple(v)) for k, v in self.restrictions.items())))
        k = self.layout.limb_count
        out = []
        for r in ds.dataset(f"{self.path}/catalog", format="parquet").to_table().to_pylist():
            lo, hi = (joined([r[f"{s}{i}"] for i in range(k)]) for s in ("lo", "hi"))
            nxt = search.next_match(lo)
            if nxt is not None and nxt <= hi:
                out.append(SlicePartition(f"{self.path}/data/slice={r['slice']}", r["slice"]))
        return out or [SlicePartition("", -1)]

    def read(self, partition: SlicePartition) -> Iterator[pa.RecordBatch]:
        if partition.number < 0:
            return
        names = [f.name for f in self.schema.fields]
        yield from ds.dataset(partition.path, format="parquet").scanner(columns=names).to_batches()


class KeyedStoreSource(DataSource):
    """Registered under the name ``keyhop``."""

    @classmethod
    def name(cls) -> str:
        return "keyhop"

    def schema(self):
        session = SparkSession.getActiveSession()
        if session is not None:
            fields = [f for f in session.read.parquet(f"{self.options['path']}/data").schema.fields if f.name != "slice"]
            return type(session.range(0).schema)(fields)
        from pyspark.sql.pandas.types import from_arrow_schema

        return from_arrow_schema(ds.dataset(f"{self.options['path']}/data", format="parquet").schema)

    def reader(self, schema) -> StoreReader:
        return StoreReader(self.options["path"].removeprefix("file:").replace("//", "/"), schema)


def register(spark: SparkSession) -> None:
    """Make the format known, with filter pushdown on."""
    from keyhop.runtime import ship

    ship(spark)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(KeyedStoreSource)
