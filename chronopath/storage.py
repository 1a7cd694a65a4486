"""Stored intermediate tables: they cut the lineage of loops and survive lost executors."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``, or the one set on the context."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        option = spark.sparkContext._jsc.sc().getCheckpointDir()
        found = option.get() if option.isDefined() else None
    if not found:
        if not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        found = f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/chronopath-scratch"  # one machine: any folder is shared
    return found.rstrip("/")


class Stored:
    """A DataFrame written as Parquet, with the numbers observed while it was written."""

    def __init__(self, df: DataFrame, name: str = "table", **measures: Column):
        spark, observation = df.sparkSession, Observation()
        self.path = f"{shared_dir(spark)}/chronopath-{name}-{uuid.uuid4().hex}"
        self.spark = spark
        df.observe(observation, F.count(F.lit(1)).alias("rows"), *(c.alias(k) for k, c in measures.items())).write.parquet(self.path)
        self.seen = {k: v or 0 for k, v in observation.get.items()}
        self.df = spark.read.schema(df.schema).parquet(self.path)

    def drop(self) -> None:
        path = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
        path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def store(df: DataFrame, name: str = "table") -> DataFrame:
    return Stored(df, name).df
