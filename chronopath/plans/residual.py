"""Edges that still matter once stable vertices are settled: those into the others."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def residual_graph(core: DataFrame, unstable: DataFrame) -> DataFrame:
    """Built up from the (few) unstable vertices; Spark broadcasts them while they are small."""
    return core.join(unstable.select(F.col("v").alias("dst")), "dst", "left_semi").select("src", "dst", "w")


def residual_by_removal(core: DataFrame, stable: DataFrame) -> DataFrame:
    """The same by taking away edges into stable vertices."""
    return core.join(stable.select(F.col("v").alias("dst")), "dst", "left_anti").select("src", "dst", "w")


def trim_additions(additions: DataFrame, unstable: DataFrame) -> DataFrame:
    return additions.join(unstable.select(F.col("v").alias("dst")), "dst", "left_semi").select(additions.columns)


def loop_edges(edges: DataFrame, unstable: DataFrame) -> DataFrame:
    """Edges with both ends unstable: a stable vertex never changes, so it sends nothing after the seed."""
    return edges.join(unstable.select(F.col("v").alias("src")), "src", "left_semi").select(edges.columns)
