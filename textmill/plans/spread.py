"""Even work on small inputs."""

from __future__ import annotations

from pyspark.sql import DataFrame


def spread(df: DataFrame) -> DataFrame:
    """df dealt evenly over the cores, if by its size it is read in fewer splits than there are cores; else df as it is.

    Only for work that is dear per row, such as counting a text's words in Python: a file of one row group is one task
    however many cores wait. The size is the planner's; a large table has more splits than cores and isn't shuffled.
    """
    spark = df.sparkSession
    cores = spark.sparkContext.defaultParallelism
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    split = spark._jsparkSession.sessionState().conf().filesMaxPartitionBytes()
    return df.repartition(cores) if size < (cores - 1) * split else df
