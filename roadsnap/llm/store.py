"""Where the operators put what they must keep between jobs: the folder that all executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir; where the session names none (tests), a local one, set once."""
    place = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not place:
        place = spark.conf.get("roadsnap.shared.dir", None)
    if not place:
        place = f"file://{tempfile.mkdtemp(prefix='roadsnap-')}"
        spark.conf.set("roadsnap.shared.dir", place)
    return place.rstrip("/")


def keep(df: DataFrame, name: str = "t") -> DataFrame:
    """Write a frame to the shared folder and read it back: it is computed once and outlives executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop(*frames: DataFrame) -> None:
    """Delete what keep() wrote, once nothing reads it any more."""
    for df in frames:
        spark = df.sparkSession
        for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
            path = spark._jvm.org.apache.hadoop.fs.Path(folder)
            path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
