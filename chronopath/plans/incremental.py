"""The streaming baseline: values of one snapshot turned into the next one's under additions and deletions.

Each vertex remembers the neighbour that gave it its value, recorded only when the
value strictly improved, so these links form a forest even where values tie. A
deleted link invalidates its whole subtree; invalid vertices start again from
their valid in-neighbours.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronopath.functions.algebra import PathAlgebra
from chronopath.plans.fixpoint import Work, candidates, iterate, relax_additions
from chronopath.storage import Stored, store


def invalidated(state: DataFrame, deleted: DataFrame) -> DataFrame:
    """Vertices whose chain of parents uses a deleted edge: the heads of such edges, then their children level by level.

    A level costs one pass over (v, parent) against the level above, which holds invalid
    vertices only, so a batch pays for the subtrees that it cuts and not for the forest.
    """
    links = state.where("parent is not null").select("v", "parent")
    level = Stored(links.join(deleted.select(F.col("src").alias("parent"), F.col("dst").alias("v")), ["parent", "v"], "left_semi").select("v"), "cut")
    found = level.df
    while level.seen["rows"]:  # ends, since parents form a forest
        level = Stored(links.join(level.df.select(F.col("v").alias("parent")), "parent", "left_semi").select("v"), "cut")
        found = found.unionByName(level.df)
    return found.distinct()


def apply_deletions(state: DataFrame, edges: DataFrame, deleted: DataFrame, algebra: PathAlgebra, work: Work | None = None) -> DataFrame:
    """State after ``deleted`` left; ``edges`` is the graph without them."""
    bad = invalidated(state, deleted)
    valid = store(state.join(bad, "v", "left_anti").select("v", "val", "parent"), "valid")
    seeds = candidates(valid, edges.join(bad.select(F.col("v").alias("dst")), "dst", "left_semi"), algebra)
    return iterate(valid, edges, algebra, work or Work(), seeds)


def apply_batch(state: DataFrame, before: DataFrame, after: DataFrame, batch: DataFrame, algebra: PathAlgebra, work: Work | None = None, fused: bool = False) -> DataFrame:
    """One step: deletions, then additions; ``fused`` relaxes once on the graph that has both."""
    added, deleted = (batch.where(F.col("op") == op).select("src", "dst", "w") for op in ("add", "del"))
    if fused:
        bad = invalidated(state, deleted)
        valid = store(state.join(bad, "v", "left_anti").select("v", "val", "parent"), "valid")
        into_bad = after.join(bad.select(F.col("v").alias("dst")), "dst", "left_semi").select("src", "dst", "w")
        return iterate(valid, after, algebra, work or Work(), candidates(valid, into_bad.unionByName(added), algebra))
    kept = before.join(deleted.select("src", "dst"), ["src", "dst"], "left_anti").select("src", "dst", "w")
    return relax_additions(apply_deletions(state, kept, deleted, algebra, work), kept, added, algebra, work)
