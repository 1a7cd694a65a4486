"""Bounds over all chosen snapshots, and what they settle.

Every path of the core exists in every snapshot, and every path of a snapshot
exists in the hull: so the core's value is reached or beaten in each snapshot, and
the hull's value is never beaten. Where the two agree a vertex is stable.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronopath.functions.algebra import PathAlgebra
from chronopath.plans.fixpoint import Work, relax_additions, solve_full


def bound_values(core: DataFrame, additions: DataFrame, source: int, algebra: PathAlgebra, work: Work | None = None) -> tuple[DataFrame, DataFrame]:
    """(core values, hull values); the hull is reached from the core by additions only."""
    lower = solve_full(core, source, algebra, work)
    return lower, relax_additions(lower, core, additions.select("src", "dst", "w").distinct(), algebra, work)


def bounds(core_state: DataFrame, hull_state: DataFrame, algebra: PathAlgebra) -> DataFrame:
    """(v, core_val, hull_val, lower, upper); null means unreached."""
    both = core_state.select("v", F.col("val").alias("core_val")).join(hull_state.select("v", F.col("val").alias("hull_val")), "v", "full")
    low, high = ("hull_val", "core_val") if algebra.direction == "min" else ("core_val", "hull_val")
    return both.select("v", "core_val", "hull_val", F.col(low).alias("lower"), F.col(high).alias("upper"))


def stable_vertices(bound: DataFrame) -> DataFrame:
    return bound.where(F.col("core_val").eqNullSafe(F.col("hull_val"))).select("v", F.col("core_val").alias("val"))


def unstable_vertices(bound: DataFrame) -> DataFrame:
    """Vertices that the hull reaches and whose bounds differ."""
    return bound.where(~F.col("core_val").eqNullSafe(F.col("hull_val"))).select("v")


def missed_unchanged(bound: DataFrame, results: DataFrame, snapshots: int) -> DataFrame:
    """Vertices with one value in all snapshots that the bounds could not settle."""
    own = results.groupBy("v").agg(F.count_distinct("val").alias("values"), F.count("*").alias("n"))
    return own.where((F.col("values") == 1) & (F.col("n") == snapshots)).join(stable_vertices(bound), "v", "left_anti").select("v")


def bounds_tree(lifetimes: DataFrame, chosen: list[int], source: int, algebra: PathAlgebra, depth: int) -> list[tuple[tuple[int, int], DataFrame]]:
    """Bounds of the window and, halving it ``depth`` times, of its parts: ((first, last), bounds)."""
    from chronopath.plans import evolve

    rows = evolve.classified(lifetimes, chosen, algebra)
    core, additions = evolve.core_graph(rows), evolve.addition_sets(rows, algebra)
    out = [((chosen[0], chosen[-1]), bounds(*bound_values(core, additions, source, algebra), algebra))]
    if depth and len(chosen) > 1:
        half = len(chosen) // 2
        for part in (chosen[:half], chosen[half:]):
            out += bounds_tree(lifetimes, part, source, algebra, depth - 1)
    return out
