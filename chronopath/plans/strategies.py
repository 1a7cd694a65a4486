"""All ways to answer a query on every chosen snapshot; they return equal results."""

from __future__ import annotations

import time
from collections.abc import Iterable
from contextlib import contextmanager
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronopath.functions.algebra import PathAlgebra
from chronopath.functions.masks import expand
from chronopath.plans import bounds as B
from chronopath.plans import concurrent as C
from chronopath.plans import evolve as E
from chronopath.plans import incremental as I
from chronopath.plans import planner as P
from chronopath.plans import residual as R
from chronopath.plans import sharing as S
from chronopath.plans.fixpoint import Work, relax_additions, solve_full
from chronopath.storage import store


@dataclass(frozen=True)
class PathQuery:
    source: int
    algebra: PathAlgebra
    snapshots: tuple[int, ...]


@dataclass
class RunStats:
    strategy: str
    algebra: str
    phase_ms: dict[str, float] = field(default_factory=dict)
    work: dict[str, Work] = field(default_factory=dict)

    @contextmanager
    def phase(self, name: str):
        began = time.perf_counter()
        yield self.work.setdefault(name, Work())
        self.phase_ms[name] = self.phase_ms.get(name, 0.0) + 1000 * (time.perf_counter() - began)

    @property
    def total_ms(self) -> float:
        return sum(self.phase_ms.values())


@dataclass
class Prepared:
    """Core values, bounds and reduced graphs of a query: what the residual strategies share."""

    core: DataFrame
    additions: DataFrame
    core_state: DataFrame
    bound: DataFrame | None = None
    unstable: DataFrame | None = None
    residual: DataFrame | None = None
    trimmed: DataFrame | None = None


def split(lifetimes: DataFrame, query: PathQuery, identity: str = "pair") -> tuple[DataFrame, DataFrame]:
    """(core, additions) as stored tables, from one aggregation over all lifetimes."""
    rows = store(E.classified(lifetimes, query.snapshots, query.algebra, identity), "classified")
    return store(E.core_graph(rows), "core"), E.addition_sets(rows, query.algebra)


def prepare(lifetimes: DataFrame, query: PathQuery, stats: RunStats, reduced: bool = True) -> Prepared:
    with stats.phase("generate") as work:
        core, additions = split(lifetimes, query)
        if not reduced:
            return Prepared(core, additions, solve_full(core, query.source, query.algebra, work))
        lower, upper = B.bound_values(core, additions, query.source, query.algebra, work)
        bound = store(B.bounds(lower, upper, query.algebra), "bounds")
        unstable = B.unstable_vertices(bound)
        residual, trimmed = store(R.residual_graph(core, unstable), "residual"), store(R.trim_additions(additions, unstable), "trimmed")
        return Prepared(core, additions, lower, bound, unstable, residual, trimmed)


def _labelled(states: dict[int, DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, (df.select("v", F.lit(i).cast("int").alias("snap"), "val") for i, df in states.items()))


def stable_rows(p: Prepared, query: PathQuery) -> DataFrame:
    grid = F.explode(F.array(*(F.lit(i).cast("int") for i in query.snapshots))).alias("snap")
    return B.stable_vertices(p.bound).where("val is not null").select("v", grid, "val")


def recompute(lifetimes, query, stats):
    with stats.phase("evaluate") as work:
        return _labelled({i: solve_full(E.snapshot(lifetimes, i), query.source, query.algebra, work) for i in query.snapshots})


def recompute_together(lifetimes, query, stats):
    """From scratch on every snapshot, in one loop over masked edges."""
    with stats.phase("evaluate") as work:
        spark = lifetimes.sparkSession
        edges = store(E.masked(lifetimes, query.snapshots).drop("chosen"), "masked")
        start = C.everywhere(spark.createDataFrame([(query.source, query.algebra.source_value)], "v long, val double"), query.snapshots)
        return expand(C.solve_concurrent(start.limit(0), start, edges, edges, query.algebra, "private", work)).select("v", "snap", "val")


def stream_inc(lifetimes, query, stats, fused: bool = False):
    wanted = sorted(query.snapshots)
    with stats.phase("evaluate") as work:
        states = {wanted[0]: solve_full(E.snapshot(lifetimes, wanted[0]), query.source, query.algebra, work, track_parent=True)}
        for before, i in zip(wanted, wanted[1:]):
            batch = store(E.batch_between(lifetimes, before, i), "batch")
            states[i] = I.apply_batch(states[before], E.snapshot(lifetimes, before), E.snapshot(lifetimes, i), batch, query.algebra, work, fused)
        return _labelled(states)


def core_direct(lifetimes, query, stats):
    p = prepare(lifetimes, query, stats, reduced=False)
    with stats.phase("evaluate") as work:
        return _labelled({i: relax_additions(p.core_state, p.core, E.addition_set(p.additions, i), query.algebra, work) for i in query.snapshots})


def _contiguous(query) -> tuple[int, int]:
    low, high = min(query.snapshots), max(query.snapshots)
    if sorted(query.snapshots) != list(range(low, high + 1)):
        raise ValueError("sharing along a tree of ranges needs a window without gaps")
    return low, high


def _tree(lifetimes, query, optimal: bool):
    low, high = _contiguous(query)
    counts = None
    if optimal:
        counts = {(r["born"], r["died"]): r["n"] for r in E.bursts_table(lifetimes).collect()}
    return S.plan_tree(low, high, counts)


def core_share(lifetimes, query, stats, optimal: bool = False):
    p = prepare(lifetimes, query, stats, reduced=False)
    with stats.phase("evaluate") as work:
        return _labelled(S.run_tree(_tree(lifetimes, query, optimal), p.core_state, p.core, p.additions, query.algebra, work))


def residual_seq(lifetimes, query, stats):
    p = prepare(lifetimes, query, stats)
    with stats.phase("evaluate") as work:
        states = {i: relax_additions(p.core_state, p.residual, E.addition_set(p.trimmed, i), query.algebra, work) for i in query.snapshots}
        return _labelled(states)


def residual_share(lifetimes, query, stats, optimal: bool = False):
    p = prepare(lifetimes, query, stats)
    with stats.phase("evaluate") as work:
        return _labelled(S.run_tree(_tree(lifetimes, query, optimal), p.core_state, p.residual, p.trimmed, query.algebra, work))


def residual_conc(lifetimes, query, stats, frontier: str = "private"):
    p = prepare(lifetimes, query, stats)
    with stats.phase("evaluate") as work:
        loop = store(R.loop_edges(C.versioned_graph(p.residual, p.trimmed, query.snapshots), p.unstable), "versioned")
        start = p.core_state.join(p.unstable, "v", "left_semi")
        settled = p.core_state.join(p.unstable, "v", "left_anti")
        solved = C.solve_concurrent(C.everywhere(settled, query.snapshots), C.everywhere(start, query.snapshots), p.trimmed, loop, query.algebra, frontier, work)
        return expand(solved).select("v", "snap", "val").unionByName(stable_rows(p, query))


def residual_conc_shared(lifetimes, query, stats):
    return residual_conc(lifetimes, query, stats, "shared")


def core_conc(lifetimes, query, stats, frontier: str = "private"):
    """All snapshots together without the reduction."""
    p = prepare(lifetimes, query, stats, reduced=False)
    with stats.phase("evaluate") as work:
        edges = store(C.versioned_graph(p.core, p.additions, query.snapshots), "versioned")
        start = C.everywhere(p.core_state, query.snapshots)
        return expand(C.solve_concurrent(start.limit(0), start, p.additions, edges, query.algebra, frontier, work)).select("v", "snap", "val")


STRATEGIES = {f.__name__: f for f in (recompute, recompute_together, stream_inc, core_direct, core_share, residual_seq, residual_share, residual_conc, residual_conc_shared, core_conc)}


def counts(p: Prepared, snapshots: int) -> P.Counts:
    return P.Counts(p.core.count(), p.additions.count(), p.bound.count(), p.unstable.count(), snapshots)


def run(strategy: str, lifetimes: DataFrame, query: PathQuery) -> tuple[DataFrame, RunStats]:
    """(v, snap, val) of every vertex reached in every chosen snapshot, and what the run took."""
    stats = RunStats(strategy, query.algebra.name)
    if strategy == "auto":
        p = prepare(lifetimes, query, stats)
        strategy = P.choose(counts(p, len(query.snapshots)))
    results = STRATEGIES[strategy](lifetimes, query, stats)
    return results.select("v", F.col("snap").cast("int").alias("snap"), F.col("val").cast("double").alias("val")), stats
