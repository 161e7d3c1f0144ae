"""Dictionaries: distinct values to consecutive codes, distributed."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def build_dictionary(df: DataFrame, column: str, ordered: bool = True, partitions: int = 16) -> DataFrame:
    """``value`` and ``code`` (from 1) of the distinct non-null values of ``column``; in value order if ``ordered``.

    Values are range-partitioned, numbered within their partition, and shifted by the number of values
    in the partitions before, so no task sees them all.
    """
    values = df.where(F.col(column).isNotNull()).select(F.col(column).alias("value")).distinct()
    parted = (values.repartitionByRange(partitions, "value") if ordered else values.repartition(partitions, "value")).withColumn("part", F.spark_partition_id())
    numbered = parted.withColumn("rank", F.row_number().over(Window.partitionBy("part").orderBy("value")))
    sizes = numbered.groupBy("part").agg(F.max("rank").alias("size"))
    # One row for each partition: the window over them is as small as their number.
    starts = sizes.select(F.col("part").alias("of_part"), F.coalesce(F.sum("size").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("first"))
    return numbered.join(F.broadcast(starts), F.col("part") == F.col("of_part")).select("value", (F.col("rank") + F.col("first")).cast("bigint").alias("code"))
