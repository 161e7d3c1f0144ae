"""Keyed stores fed by streams: every micro-batch adds slices of its own, sorted by key, with their catalog rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from keyhop.functions.curve import KeyLayout
from keyhop.sources.store import KeyedStore, catalog_of


#: Slice numbers of a batch start at its number times this.
SLICES_PER_BATCH = 1_000_000


def append_run(layout: KeyLayout, path: str, rows_per_slice: int = 4_000_000) -> Callable[[DataFrame, int], None]:
    """A ``foreachBatch`` function: a batch becomes slices of its own, sorted by key, and catalog rows of its own.

    The batch is range-partitioned by key into as many slices as its rows need. One that is delivered
    again overwrites its own folders and no others; earlier batches are neither read nor written.
    """

    def write(batch: DataFrame, number: int) -> None:
        keys = layout.key_columns
        slices = max(1, -(-batch.count() // rows_per_slice))
        keyed = layout.encode(batch)
        keyed = keyed.repartitionByRange(slices, *keys, F.xxhash64(*batch.columns)) if slices > 1 else keyed.repartition(1)
        keyed = keyed.withColumn("slice", F.spark_partition_id() + number * SLICES_PER_BATCH).sortWithinPartitions("slice", *keys)
        data = f"{path}/data/batch={number}"
        keyed.write.mode("overwrite").partitionBy("slice").parquet(data)
        catalog_of(batch.sparkSession.read.parquet(data), keys).write.mode("overwrite").parquet(f"{path}/catalog/batch={number}")

    return write


def stream_store(source: DataFrame, layout: KeyLayout, path: str, checkpoint: str) -> KeyedStore:
    """Take in all that ``source`` (a streaming frame) has and return the store; batches bring their own catalog rows."""
    spark = source.sparkSession
    spark.createDataFrame([(layout.to_json(),)], "layout string").coalesce(1).write.mode("overwrite").text(f"{path}/layout")
    query = source.writeStream.foreachBatch(append_run(layout, path)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return KeyedStore(spark, path, layout)


def finished(result: DataFrame, path: str, mode: str = "append") -> DataFrame:
    """Run a streaming frame over all that its source has, into Parquet below ``path``, and read it.

    ``complete`` is for aggregates: the last batch's whole result is what counts, open windows included.
    """
    spark = result.sparkSession
    writer = result.writeStream.outputMode(mode).option("checkpointLocation", f"{path}/state").trigger(availableNow=True)
    if mode == "complete":
        writer = writer.foreachBatch(lambda batch, number: batch.write.mode("overwrite").parquet(f"{path}/out"))
    else:
        writer = writer.format("parquet").option("path", f"{path}/out")
    writer.start().awaitTermination()
    return spark.read.schema(result.schema).parquet(f"{path}/out")


def event_stream(spark: SparkSession, sf_dir: str, late: str = "1 hour") -> DataFrame:
    """The events as a stream, with a watermark on ``ts``."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    source = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return source.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
