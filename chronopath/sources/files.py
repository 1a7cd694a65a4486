"""Readers and writers of edges and results, and a data source of synthetic updates."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from chronopath.schemas import BATCHES, EDGES, require


def read_edges(spark: SparkSession, path: str, kind: str = "parquet", sep: str = "\t") -> DataFrame:
    """Edges from parquet, orc, json, csv or text lines ``src<sep>dst[<sep>w]``; lines that start with # are left out."""
    if kind == "text":
        part = F.split("value", sep)
        lines = spark.read.text(path).where(~F.col("value").startswith("#") & (F.trim("value") != ""))
        return lines.select(part[0].cast("long").alias("src"), part[1].cast("long").alias("dst"), F.coalesce(F.try_element_at(part, F.lit(3)).cast("double"), F.lit(1.0)).alias("w"))
    reader = spark.read.schema(EDGES)
    return require(reader.csv(path, sep=sep) if kind == "csv" else reader.format(kind).load(path), EDGES)


def write_edges(edges: DataFrame, path: str, kind: str = "parquet", sep: str = "\t") -> None:
    if kind == "text":
        edges.select(F.concat_ws(sep, "src", "dst", "w").alias("value")).write.text(path)
    elif kind == "csv":
        edges.write.csv(path, sep=sep)
    else:
        edges.write.format(kind).save(path)


def write_bucketed(edges: DataFrame, name: str, buckets: int, key: str = "src") -> None:
    """A table whose joins on ``key`` need no shuffle with another of as many buckets."""
    edges.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(name)


def write_batches(batches: DataFrame, path: str) -> None:
    """Update batches in a folder for each step."""
    batches.write.partitionBy("step").parquet(path)


def read_batches(spark: SparkSession, path: str, first: int, last: int) -> DataFrame:
    """Only the folders of the steps asked for are read."""
    return require(spark.read.parquet(path).where(F.col("step").between(first, last)), BATCHES)


def write_results(results: DataFrame, path: str) -> None:
    results.write.partitionBy("snap").parquet(path)


class SyntheticUpdates(DataSource):
    """Random update batches, the same for the same options: vertices, steps, batch, seed, partitions."""

    @classmethod
    def name(cls) -> str:
        return "synthetic_updates"

    def schema(self) -> str:
        return "step int, op string, src long, dst long, w double"

    def reader(self, schema) -> DataSourceReader:
        return _UpdatesReader({k: int(self.options.get(k, d)) for k, d in (("vertices", 100), ("steps", 4), ("batch", 10), ("seed", 1), ("partitions", 2))})


class _UpdatesReader(DataSourceReader):
    def __init__(self, options: dict[str, int]):
        self.options = options

    def partitions(self):
        return [InputPartition(i) for i in range(self.options["partitions"])]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        import random

        o = self.options
        for step in range(1 + partition.value, o["steps"] + 1, o["partitions"]):
            draw = random.Random(o["seed"] * 1_000_003 + step)
            for k in range(o["batch"]):
                src, dst = draw.randrange(o["vertices"]), draw.randrange(o["vertices"] - 1)
                yield step, "add" if k % 2 == 0 else "del", src, dst + (dst >= src), float(draw.randint(1, 9))
