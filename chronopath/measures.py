"""Measures of a query on changing graphs; counts are DataFrames of one row, times come from RunStats."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronopath.plans.bounds import stable_vertices


def unchanged(results: DataFrame, snapshots: int) -> DataFrame:
    """(v): one value in all snapshots."""
    own = results.groupBy("v").agg(F.count("*").alias("n"), F.min("val").alias("a"), F.max("val").alias("b"))
    return own.where((F.col("n") == snapshots) & (F.col("a") == F.col("b"))).select("v")


def unchanged_share(results: DataFrame, snapshots: int) -> DataFrame:
    """vertices reached in some snapshot, unchanged ones, and their share."""
    own = results.groupBy("v").agg(((F.count("*") == snapshots) & (F.min("val") == F.max("val"))).cast("long").alias("same"))
    return own.agg(F.count("*").alias("vertices"), F.sum("same").alias("unchanged"), F.avg(F.col("same").cast("double")).alias("share"))


def detection(bound: DataFrame, results: DataFrame, snapshots: int) -> DataFrame:
    """stable, unchanged, found = stable and unchanged, unsafe = stable but changed (must be 0), recall."""
    stable = stable_vertices(bound).where("val is not null").select("v", F.lit(1).alias("s"))
    same = unchanged(results, snapshots).select("v", F.lit(1).alias("u"))
    both = stable.join(same, "v", "full")
    counted = both.agg(F.count("s").alias("stable"), F.count("u").alias("unchanged"), F.count_if(F.col("s").isNotNull() & F.col("u").isNotNull()).alias("found"))
    return counted.withColumn("unsafe", F.col("stable") - F.col("found")).withColumn("recall", F.try_divide("found", "unchanged"))


def sizes(core: DataFrame, additions: DataFrame, bound: DataFrame, unstable: DataFrame, residual: DataFrame, trimmed: DataFrame) -> DataFrame:
    """Counts and shares of the reduced graph against the core graph; each part is aggregated alone."""
    bits = lambda df, name: df.agg(F.count("*").alias(f"{name}_distinct"), F.coalesce(F.sum(F.bit_count("mask")), F.lit(0)).alias(f"{name}_total"))
    parts = [core.agg(F.count("*").alias("core_edges")), residual.agg(F.count("*").alias("residual_edges")), bound.agg(F.count("*").alias("vertices")), unstable.agg(F.count("*").alias("unstable")), bits(additions, "added"), bits(trimmed, "trimmed")]
    out = parts[0]
    for part in parts[1:]:
        out = out.join(part)
    return out.withColumns({"edge_share": F.try_divide("residual_edges", "core_edges"), "vertex_share": F.try_divide("unstable", "vertices"), "redundant": F.col("added_total") - F.col("added_distinct"), "kept_share": F.try_divide("trimmed_total", "added_total")})


def bound_widths(bound: DataFrame, edges: list[float]) -> DataFrame:
    """(bucket, n) of upper - lower over unstable vertices with both bounds."""
    width = F.col("upper") - F.col("lower")
    bucket = sum((F.when(width >= e, 1).otherwise(0) for e in edges), F.lit(0))
    return bound.where("core_val is not null and core_val <> hull_val").groupBy(bucket.alias("bucket")).agg(F.count("*").alias("n"))


def average_degree(edges: DataFrame) -> DataFrame:
    ends = edges.select(F.explode(F.array("src", "dst")).alias("v")).agg(F.count_distinct("v").alias("vertices"))
    return edges.agg(F.count("*").alias("edges")).join(ends).withColumn("degree", F.try_divide("edges", "vertices")).withColumn("degree_both", 2 * F.try_divide("edges", "vertices"))


def compression(state_rows: int, vertices: int, snapshots: int) -> float:
    """Rows of mask-compressed state against one value a vertex and snapshot."""
    return state_rows / max(1, vertices * snapshots)


def speedup(baseline_ms: float, ms: float) -> float:
    return baseline_ms / ms


def generation_share(stats) -> float:
    return stats.phase_ms.get("generate", 0.0) / max(1e-9, stats.total_ms)


def redundant_evaluations(shared, private) -> int:
    """Candidates that the shared frontier tries beyond those of private ones."""
    return shared.evaluations - private.evaluations
