"""A running sum over a global order without moving all rows to one task."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .components import reliable


def prefix_sum(df: DataFrame, order: list[str], value: Column, name: str, partitions: int | None = None) -> DataFrame:
    """df with `name`: the sum of value over all rows before each row in the order (ties in any order of equal rows).

    Rows are dealt by ranges of the order; each range is summed by itself and the sums of the ranges before it (one
    number a range) are added. Returns a stored table, because a range number must not change between its two uses.
    """
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = reliable(df.withColumn("value_", value))  # dealing by ranges reads its input twice
    ranged = reliable(rows.repartitionByRange(n, *order).withColumn("range_", F.spark_partition_id()))
    local = F.sum("value_").over(Window.partitionBy("range_").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1))
    totals = ranged.groupBy("range_").agg(F.sum("value_").alias("total_"))
    before = totals.select(F.col("range_").alias("r_"), F.coalesce(F.sum("total_").over(Window.orderBy("range_").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("offset_"))
    return ranged.withColumn("local_", F.coalesce(local, F.lit(0))).join(F.broadcast(before), F.col("range_") == F.col("r_")).withColumn(name, F.col("local_") + F.col("offset_")).drop("value_", "range_", "local_", "r_", "offset_")
