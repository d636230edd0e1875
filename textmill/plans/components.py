"""Connected components of an edge table by star contraction."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_base(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir, which the driver and all executors see; set here only where it is unset."""
    base = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors see")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="textmill-"))  # one machine: tests and the bench
        base = spark.sparkContext.getCheckpointDir()
    return base.rstrip("/")


def reliable(df: DataFrame) -> DataFrame:
    """df as a table in the shared folder: cuts the lineage, survives the loss of an executor."""
    path = f"{shared_base(df.sparkSession)}/{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.stored_at = path
    return out


def dropped(*tables: DataFrame) -> None:
    """Removes the files of reliable() tables that nothing reads any more."""
    for df in tables:
        context = df.sparkSession.sparkContext
        path = context._jvm.org.apache.hadoop.fs.Path(df.stored_at)
        path.getFileSystem(context._jsc.hadoopConfiguration()).delete(path, True)


def connected_components(edges: DataFrame) -> DataFrame:
    """(src, dst) -> (id, comp): comp is the least id of the component. Large-star and small-star steps alternate until
    a round leaves the edges as they are; every round is one checkpoint and two joins over the edges."""

    def toward_least(e: DataFrame) -> DataFrame:
        least = e.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("a_"), F.least("a", "m").alias("m"))
        return e.join(least, F.col("a") == F.col("a_")).select("a", "b", "m")

    e = reliable(edges.filter("src <> dst").select(F.greatest("src", "dst").alias("a"), F.least("src", "dst").alias("b")).distinct())
    before = None
    while True:
        large = toward_least(e.union(e.select("b", "a"))).filter("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        small = toward_least(large)
        last = e
        e = reliable(small.filter("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).union(small.select("a", "m")).filter("a <> b").distinct())
        dropped(last)
        now = e.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if now == before:
            return e.toDF("id", "comp").union(e.select(F.col("b").alias("id"), F.col("b").alias("comp")).distinct())
        before = now
