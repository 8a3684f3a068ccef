"""Cutting lineage: tables written to the folder that all executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession, Window, functions as F


def shared_dir(spark: SparkSession) -> str:
    """The session's spark.checkpoint.dir; a local folder is made only where that is unset, once a session."""
    place = spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.conf.get("roadsnap.loops.dir", None)
    if not place:
        place = f"file://{tempfile.mkdtemp(prefix='roadsnap-loops-')}"
        spark.conf.set("roadsnap.loops.dir", place)
    return place.rstrip("/")


def cut(df: DataFrame) -> DataFrame:
    """Write and read back: later rounds of a loop start from files, so a lost executor repeats one round only."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/round-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop(*frames: DataFrame) -> None:
    """Delete what cut() wrote, once nothing reads it any more."""
    for df in frames:
        spark = df.sparkSession
        for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
            path = spark._jvm.org.apache.hadoop.fs.Path(folder)
            path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def ranked(df: DataFrame, *by: str, name: str = "rank") -> DataFrame:
    """`df` with each row's place, from 0, in the order of columns that tell all rows apart.

    A global sort and one number per partition; a window without partitions would bring all rows to one task.
    """
    at = cut(df.orderBy(*by).withColumn("_at", F.monotonically_increasing_id()).withColumn("_part", F.shiftright("_at", 33)))
    size = at.groupBy("_part").agg(F.count("*").alias("_n"), F.min("_at").alias("_least"))
    before = size.select("_part", "_least", (F.sum("_n").over(Window.orderBy("_part")) - F.col("_n")).alias("_before"))  # a row per partition
    return at.join(F.broadcast(before), "_part").withColumn(name, F.col("_before") + F.col("_at") - F.col("_least")).drop("_part", "_at", "_least", "_before")
