"""Relaxation loops: full evaluation from a source, and addition-only relaxation.

A round is one plan: frontier joined with edges on their source, candidates and
values combined by vertex in one aggregation (partially before its shuffle), and
written. The number of rows that changed is observed while
they are written; nothing else comes to the driver.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronopath.functions.algebra import PathAlgebra
from chronopath.storage import Stored

MAX_ROUNDS = 10_000


@dataclass
class Work:
    """Counters of a run."""

    rounds: int = 0
    evaluations: int = 0
    changed: int = 0
    notes: dict = field(default_factory=dict)


def start_state(spark, source: int, algebra: PathAlgebra) -> DataFrame:
    return spark.createDataFrame([(source, algebra.source_value)], "v long, val double")


def candidates(frontier: DataFrame, edges: DataFrame, algebra: PathAlgebra) -> DataFrame:
    """(v, cand, sender): what frontier vertices offer to their neighbours."""
    return frontier.select(F.col("v").alias("sender"), "val").join(edges, F.col("sender") == F.col("src")).select(F.col("dst").alias("v"), algebra.extend(F.col("val"), F.col("w")).alias("cand"), "sender")


def _relax(state: DataFrame, sent: DataFrame, algebra: PathAlgebra) -> DataFrame:
    """State merged with candidates by one aggregation; ``fresh`` marks rows that got better, ``met`` counts candidates."""
    parents, none = "parent" in state.columns, F.lit(None)
    rows = state.select("v", F.col("val").alias("old"), (F.col("parent") if parents else none.cast("long")).alias("old_parent"), none.cast("double").alias("cand"), none.cast("long").alias("sender"))
    rows = rows.unionByName(sent.select("v", none.cast("double").alias("old"), none.cast("long").alias("old_parent"), "cand", "sender"))
    found = [F.max("old").alias("old"), algebra.keep(F.col("cand")).alias("cand"), F.count("cand").alias("met")]
    if parents:  # of equal offers that of the smallest sender
        offer = F.when(F.col("cand").isNotNull(), F.struct(algebra.cost(F.col("cand")), "sender"))
        found += [F.max("old_parent").alias("old_parent"), F.min_by("sender", offer).alias("sender")]
    fresh = F.col("cand").isNotNull() & (F.col("old").isNull() | algebra.better(F.col("cand"), F.col("old")))
    columns = ["v", F.when(fresh, F.col("cand")).otherwise(F.col("old")).alias("val"), fresh.alias("fresh"), "met"]
    if parents:
        columns.append(F.when(fresh, F.col("sender")).otherwise(F.col("old_parent")).alias("parent"))
    return rows.groupBy("v").agg(*found).select(*columns)


def iterate(state: DataFrame, edges: DataFrame, algebra: PathAlgebra, work: Work, first: DataFrame | None = None) -> DataFrame:
    """Relax until nothing changes. ``first``: candidates to begin with; by default all of ``state`` is the frontier."""
    stored, sent = None, candidates(state, edges, algebra) if first is None else first
    for _ in range(MAX_ROUNDS):
        after = Stored(_relax(state, sent, algebra), "state", fresh=F.sum(F.col("fresh").cast("long")), met=F.sum("met"))
        if stored is not None:
            stored.drop()
        stored, state = after, after.df.drop("fresh", "met")
        work.rounds += 1
        work.changed += after.seen["fresh"]
        work.evaluations += after.seen["met"]
        if not after.seen["fresh"]:
            return state
        sent = candidates(after.df.where("fresh"), edges, algebra)
    raise RuntimeError("relaxation did not end: the algebra breaks its contract")


def solve_full(edges: DataFrame, source: int, algebra: PathAlgebra, work: Work | None = None, track_parent: bool = False) -> DataFrame:
    """(v, val[, parent]) of every vertex that the source reaches."""
    state = start_state(edges.sparkSession, source, algebra)
    if track_parent:
        state = state.withColumn("parent", F.lit(None).cast("long"))
    return iterate(state, edges, algebra, work or Work())


def relax_additions(state: DataFrame, base: DataFrame, added: DataFrame, algebra: PathAlgebra, work: Work | None = None) -> DataFrame:
    """Values after edges are added: only added edges are tried first, then what they improve spreads."""
    return iterate(state, base.unionByName(added), algebra, work or Work(), candidates(state, added, algebra))
