"""All snapshots at once on a versioned graph with mask-compressed values.

A row (v, val, word, mask) says that v has this value in the snapshots of the mask;
masks of a vertex do not overlap, so a vertex with k different values has k rows,
however many snapshots there are. A round sends frontier rows along edges that own
some of their snapshots, combines equal candidates by OR, and lets better values
claim snapshots before worse ones by a running OR over each vertex' few rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from chronopath.functions.algebra import PathAlgebra
from chronopath.functions.masks import word_table
from chronopath.plans.fixpoint import MAX_ROUNDS, Work
from chronopath.storage import Stored


def versioned_graph(common: DataFrame, additions: DataFrame, chosen) -> DataFrame:
    """(src, dst, w, word, mask) of edges of all snapshots and of some."""
    words = F.broadcast(word_table(common.sparkSession, chosen))
    whole = common.join(words).select("src", "dst", "w", "word", F.col("chosen").alias("mask"))
    return whole.unionByName(additions.select("src", "dst", "w", "word", "mask")).groupBy("src", "dst", "w", "word").agg(F.bit_or("mask").alias("mask"))


def everywhere(state: DataFrame, chosen) -> DataFrame:
    """Values that hold in all chosen snapshots, as masked state."""
    return state.join(F.broadcast(word_table(state.sparkSession, chosen))).select("v", "val", "word", F.col("chosen").alias("mask"))


def send(frontier: DataFrame, edges: DataFrame, algebra: PathAlgebra) -> DataFrame:
    """(v, val, word, mask, met): candidates by destination and value."""
    out = edges.select("src", "word", "dst", "w", F.col("mask").alias("owned"))
    met = frontier.select(F.col("v").alias("src"), "word", "val", "mask").join(out, ["src", "word"]).withColumn("mask", F.col("mask").bitwiseAND(F.col("owned"))).where("mask <> 0")
    return met.groupBy(F.col("dst").alias("v"), algebra.extend(F.col("val"), F.col("w")).alias("val"), "word").agg(F.bit_or("mask").alias("mask"), F.count("*").alias("met"))


def resolve(state: DataFrame, sent: DataFrame, algebra: PathAlgebra) -> DataFrame:
    """(v, val, word, mask, delta, met): what each value keeps, and the snapshots in which it is new."""
    none = F.lit(0).cast("long")
    rows = state.select("v", "val", "word", F.col("mask").alias("old"), none.alias("new"), none.alias("met")).unionByName(sent.select("v", "val", "word", none.alias("old"), F.col("mask").alias("new"), "met"))
    rows = rows.groupBy("v", "word", "val").agg(F.bit_or("old").alias("old"), F.bit_or("new").alias("new"), F.sum("met").alias("met"))
    before = Window.partitionBy("v", "word").orderBy(algebra.cost(F.col("val"))).rowsBetween(Window.unboundedPreceding, -1)
    taken = F.coalesce(F.bit_or(F.col("old").bitwiseOR(F.col("new"))).over(before), none)
    rows = rows.withColumn("mask", F.col("old").bitwiseOR(F.col("new")).bitwiseAND(F.bitwise_not(taken)))
    return rows.withColumn("delta", F.col("mask").bitwiseAND(F.bitwise_not("old"))).select("v", "val", "word", "mask", "delta", "met")


def solve_concurrent(settled: DataFrame, state: DataFrame, seeds: DataFrame, edges: DataFrame, algebra: PathAlgebra, frontier: str = "private", work: Work | None = None) -> DataFrame:
    """(v, val, word, mask) of the vertices that may change.

    ``settled`` sends along ``seeds`` once; ``state`` are the changing vertices' values at
    the start; ``frontier``: each row's own new snapshots, or all rows of active vertices ('shared').
    """
    work = work or Work()
    sent, stored = send(settled.unionByName(state), seeds, algebra), None
    for _ in range(MAX_ROUNDS):
        rows = resolve(state, sent, algebra)
        after = Stored(rows, "masked", fresh=F.sum((F.col("delta") != 0).cast("long")), met=F.sum("met"))
        if stored is not None:
            stored.drop()
        stored, state = after, after.df.where("mask <> 0").select("v", "val", "word", "mask")
        work.rounds += 1
        work.changed += after.seen["fresh"]
        work.evaluations += after.seen["met"]
        if not after.seen["fresh"]:
            return state
        if frontier == "shared":
            active = state.join(after.df.where("delta <> 0").select("v").distinct(), "v", "left_semi")
        else:
            active = after.df.where("delta <> 0").select("v", "val", "word", F.col("delta").alias("mask"))
        sent = send(active, edges, algebra)
    raise RuntimeError("relaxation did not end: the algebra breaks its contract")
