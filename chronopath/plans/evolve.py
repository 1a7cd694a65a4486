"""How a graph changes: lifetimes, update scripts, batches, and the core and hull of chosen snapshots.

A window of snapshots is one table of lifetimes, not a table for each snapshot.
Whether an edge is in all chosen snapshots (core), in some (hull) or in some but
not all (additions) is read off the bits of its lifetimes in one aggregation.
"""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from chronopath.functions.algebra import PathAlgebra
from chronopath.functions.masks import mask_of, word_table
from chronopath.storage import store


def mix(seed: int) -> Column:
    """Portable integer scrambling of a pair, the same in any SQL engine."""
    return F.pmod(F.pmod(F.col("src") * 1000003 + F.col("dst") * 7919 + seed, F.lit(1000000007)) * 48271, F.lit(2147483647))


def first_ranked(df: DataFrame, order: list[Column], n: int) -> DataFrame:
    """The first n rows in an order with their exact ``rank`` from 0.

    Rows are dealt out by ranges of the order; each range is numbered by itself and
    starts after the rows of the ranges before it, so no task sorts them all.
    """
    cut = df.withColumns({f"_o{i}": c for i, c in enumerate(order)})
    keys = [f"_o{i}" for i in range(len(order))]
    ranges = store(cut.repartitionByRange(*keys).withColumn("_part", F.spark_partition_id()), "ranges")
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    starts = ranges.groupBy("_part").agg(F.count("*").alias("_n")).select("_part", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_start")).where(F.col("_start") < n)
    inside = F.row_number().over(Window.partitionBy("_part").orderBy(*keys)) - 1
    return ranges.join(F.broadcast(starts), "_part").withColumn("rank", inside + F.col("_start")).where(F.col("rank") < n).drop("_part", "_start", *keys)


def scripted(edges: DataFrame, snapshots: int, batch: int, seed: int = 42) -> DataFrame:
    """Lifetimes under a fixed script: each step adds batch/2 edges and deletes batch/2 others."""
    half, steps = batch // 2, snapshots - 1
    ranked = first_ranked(edges, [mix(seed), F.col("src"), F.col("dst")], 2 * half * steps)
    late, step = F.col("rank") < half * steps, (1 + F.floor(F.col("rank") / max(1, half)) % max(1, steps)).cast("int")
    changed = ranked.select("src", "dst", F.when(late, step).otherwise(0).alias("born"), F.when(late, snapshots).otherwise(step).alias("died"))
    return edges.join(changed, ["src", "dst"], "left").select("src", "dst", "w", F.coalesce("born", F.lit(0)).alias("born"), F.coalesce("died", F.lit(snapshots)).alias("died"))


def flapping(edges: DataFrame, snapshots: int, batch: int, seed: int = 42) -> DataFrame:
    """As ``scripted``; an edge that dies before the last but one step returns two steps later with its weight plus one."""
    base = scripted(edges, snapshots, batch, seed)
    back = base.where(F.col("died") < snapshots - 2).select("src", "dst", (F.col("w") + 1).alias("w"), (F.col("died") + 2).alias("born"), F.lit(snapshots).alias("died"))
    return base.unionByName(back)


def sliding(timed: DataFrame, width: int, slide: int, snapshots: int) -> DataFrame:
    """Edges with a time ``at`` are alive in snapshot i while ``at`` lies in [i * slide, i * slide + width).

    Overlapping lives of a pair merge; the merged life has the smallest weight."""
    at = F.col("at")
    lives = timed.select("src", "dst", "w", F.greatest(F.lit(0), F.floor((at - width) / slide) + 1).cast("int").alias("born"), F.least(F.lit(snapshots), F.floor(at / slide) + 1).cast("int").alias("died")).where("born < died")
    own = Window.partitionBy("src", "dst").orderBy("born", "died", "w")
    reach = F.max("died").over(own.rowsBetween(Window.unboundedPreceding, -1))
    marked = lives.withColumn("new", F.coalesce(F.col("born") > reach, F.lit(True)).cast("int")).withColumn("island", F.sum("new").over(own.rowsBetween(Window.unboundedPreceding, 0)))
    return marked.groupBy("src", "dst", "island").agg(F.min("w").alias("w"), F.min("born").alias("born"), F.max("died").alias("died")).drop("island")


def grow_only(edges: DataFrame, snapshots: int, batch: int, seed: int = 42) -> DataFrame:
    return scripted(edges, snapshots, batch, seed).withColumn("died", F.lit(snapshots))


def shrink_only(edges: DataFrame, snapshots: int, batch: int, seed: int = 42) -> DataFrame:
    return scripted(edges, snapshots, batch, seed).withColumn("born", F.lit(0))


def frozen(edges: DataFrame, snapshots: int) -> DataFrame:
    return edges.select("src", "dst", "w", F.lit(0).alias("born"), F.lit(snapshots).alias("died"))


def batches(lifetimes: DataFrame, snapshots: int) -> DataFrame:
    """(step, op, src, dst, w): step i turns snapshot i - 1 into i."""
    added = lifetimes.where("born > 0").select(F.col("born").alias("step"), F.lit("add").alias("op"), "src", "dst", "w")
    deleted = lifetimes.where(F.col("died") < snapshots).select(F.col("died").alias("step"), F.lit("del").alias("op"), "src", "dst", "w")
    return added.unionByName(deleted)


def batch_between(lifetimes: DataFrame, before: int, after: int) -> DataFrame:
    """(op, src, dst, w): what turns one snapshot into a later one, read off the lives that begin or end between them."""
    here, there = ((F.col("born") <= i) & (F.col("died") > i) for i in (before, after))
    changed = lifetimes.where(here != there)
    return changed.select(F.when(here, F.lit("del")).otherwise(F.lit("add")).alias("op"), "src", "dst", "w")


def lifetimes_from_batches(base: DataFrame, steps: DataFrame, snapshots: int) -> DataFrame:
    """Lives of a base graph under batches; a deletion ends the life that its pair has then."""
    events = base.select(F.lit(0).alias("step"), F.lit("add").alias("op"), "src", "dst", "w").unionByName(steps)
    own = Window.partitionBy("src", "dst").orderBy("step", F.desc("op"))  # within a step, deletions come first
    ends = events.withColumn("died", F.coalesce(F.lead("step").over(own), F.lit(snapshots)))
    return ends.where("op = 'add'").select("src", "dst", "w", F.col("step").alias("born"), "died")


def snapshot(lifetimes: DataFrame, i: int) -> DataFrame:
    return lifetimes.where((F.col("born") <= i) & (F.col("died") > i)).select("src", "dst", "w")


def masked(lifetimes: DataFrame, chosen: Iterable[int]) -> DataFrame:
    """(src, dst, w, word, mask, chosen): bits of the chosen snapshots in which each edge has each weight."""
    words = F.broadcast(word_table(lifetimes.sparkSession, chosen))  # a row for each 64 snapshots
    bits = lifetimes.join(words).withColumn("mask", mask_of().bitwiseAND(F.col("chosen")))
    return bits.where("mask <> 0").groupBy("src", "dst", "w", "word", "chosen").agg(F.bit_or("mask").alias("mask"))


def classified(lifetimes: DataFrame, chosen: Iterable[int], algebra: PathAlgebra, identity: str = "pair") -> DataFrame:
    """One row per (pair, weight, word) with the pair's ``in_all`` (alive in all chosen snapshots), worst and best weight.

    ``identity='triple'`` treats another weight as another edge."""
    chosen = list(chosen)
    keys = ["src", "dst"] if identity == "pair" else ["src", "dst", "w"]
    bits = masked(lifetimes, chosen)
    pairs = bits.groupBy(*keys).agg(F.sum(F.bit_count("mask")).alias("alive"), algebra.worst_weight(F.col("w")).alias("worst"), algebra.best_weight(F.col("w")).alias("best"))
    return bits.join(pairs, keys).withColumn("in_all", F.col("alive") == len(set(chosen))).drop("alive", "chosen")


def core_graph(rows: DataFrame) -> DataFrame:
    """Edges of every snapshot, a pair at its worst weight, out of ``classified`` rows."""
    return rows.where("in_all").select("src", "dst", F.col("worst").alias("w")).distinct()


def hull_graph(rows: DataFrame) -> DataFrame:
    """Edges of any snapshot, a pair at its best weight."""
    return rows.select("src", "dst", F.col("best").alias("w")).distinct()


def addition_sets(rows: DataFrame, algebra: PathAlgebra) -> DataFrame:
    """(src, dst, w, word, mask): edges that core lacks, or has at a worse weight, with their snapshots."""
    beyond = ~F.col("in_all") | algebra.weight_better(F.col("w"), F.col("worst"))
    return rows.where(beyond).select("src", "dst", "w", "word", "mask")


def addition_set(additions: DataFrame, i: int) -> DataFrame:
    """The additions of one snapshot."""
    return additions.where((F.col("word") == i // 64) & (F.call_function("bit_get", F.col("mask"), F.lit(i % 64)) == 1)).select("src", "dst", "w")


def bursts_table(lifetimes: DataFrame) -> DataFrame:
    """(born, died, n): at most one row for each pair of steps; all that the sharing tree needs."""
    return lifetimes.groupBy("born", "died").agg(F.count("*").alias("n"))
