"""What the session offers: table reading, the shared scratch folder, shipping the package to executors."""

from __future__ import annotations

import gc
import os
import tempfile
import uuid
import zipfile
from pathlib import Path

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

_SHIPPED: set[str] = set()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The Parquet table ``name`` below ``sf_dir``, by any path that Spark can read."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ship(spark: SparkSession) -> None:
    """Make this package importable in the executors' Python workers, once per application."""
    context = spark.sparkContext
    if context.applicationId in _SHIPPED:
        return
    root = Path(__file__).resolve().parent
    target = os.path.join(tempfile.mkdtemp(), "keyhop_pkg.zip")
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as archive:
        for path in sorted(root.rglob("*.py")):
            archive.write(path, str(Path(root.name) / path.relative_to(root)))
    context.addPyFile(target)
    _SHIPPED.add(context.applicationId)


class Scratch:
    """Intermediate tables as Parquet in the folder that driver and executors share.

    The folder is the session's ``spark.checkpoint.dir``; only where that is unset (tests, a single
    machine) a temporary folder of this machine is taken. A saved table cuts the lineage: after the
    loss of an executor its rows are read again, not computed again.
    """

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
        if not base:
            base = os.path.join(tempfile.gettempdir(), "keyhop-scratch")
        self.root = f"{base.rstrip('/')}/{label}-{uuid.uuid4().hex[:12]}"
        self.saved: list[str] = []

    def path(self, name: str) -> str:
        return f"{self.root}/{name}"

    def save(self, df: DataFrame, name: str) -> DataFrame:
        """Write ``df`` and return the DataFrame that reads it back."""
        df.write.mode("overwrite").option("compression", "zstd").parquet(self.path(name))
        self.saved.append(name)
        return self.spark.read.schema(df.schema).parquet(self.path(name))

    def drop(self, name: str = "") -> None:
        """Delete one saved table, or all of them; callers make sure that nothing reads it any more."""
        self.saved = [x for x in self.saved if name and x != name]
        where = self.path(name) if name else self.root
        jvm = self.spark._jvm
        folder = jvm.org.apache.hadoop.fs.Path(where)
        folder.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(folder, True)

    def release(self) -> None:
        """Let Spark delete the shuffle files of steps whose results are saved; else they wait for the driver's next full collection."""
        gc.collect()
        pa.default_memory_pool().release_unused()
        self.spark._jvm.System.gc()

    def keep(self, *names: str) -> None:
        """Delete all saved tables but these."""
        for name in [x for x in self.saved if x not in names]:
            self.drop(name)
