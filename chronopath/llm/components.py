"""Connected components of an edge table, by rounds of large-star and small-star hooking."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronopath.llm.common import Scratch

MAX_ROUNDS = 60


def _large(edges: DataFrame) -> DataFrame:
    """Each larger neighbour of a node is tied to the smallest in its neighbourhood."""
    both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
    return both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))


def _small(edges: DataFrame) -> DataFrame:
    """Smaller neighbours of a node, and the node, are tied to the smallest of them."""
    least = edges.groupBy("a").agg(F.min("b").alias("m"))
    tied = edges.join(least, "a").where("b > m").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return tied.unionByName(least.select("a", F.col("m").alias("b")))


def components(edges: DataFrame, scratch: Scratch | None = None) -> DataFrame:
    """(id, component) of every end of (a, b); the component is its smallest id. The result is a stored table."""
    scratch = scratch or Scratch(edges.sparkSession)
    falling = lambda e: e.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    now, seen = scratch.keep(falling(edges), "edges"), None
    for _ in range(MAX_ROUNDS):
        after, state = scratch.observed(falling(_small(falling(_large(now)))), "edges", n=F.count(F.lit(1)), mark=F.bit_xor(F.xxhash64("a", "b")))
        scratch.drop(now)
        now = after
        if state == seen:
            break
        seen = state
    else:
        raise RuntimeError("components did not settle")
    out = scratch.keep(now.select(F.col("a").alias("id"), F.col("b").alias("component")).unionByName(now.select(F.col("b").alias("id"), F.col("b").alias("component"))).distinct(), "components")
    scratch.drop(now)
    return out
