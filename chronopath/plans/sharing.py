"""Sharing of additions between neighbouring snapshots along a tree of ranges.

Node [i, j] has the edges alive through all of i .. j; its additions are those that
its parent lacks. The tree is planned on the driver from counts of lifetimes by
(born, died), at most one for each pair of steps.
"""

from __future__ import annotations

from functools import cache

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronopath.functions.algebra import PathAlgebra
from chronopath.plans.evolve import addition_set
from chronopath.plans.fixpoint import Work, relax_additions


def alive_through(counts: dict[tuple[int, int], int], low: int, high: int) -> int:
    return sum(n for (born, died), n in counts.items() if born <= low and died > high)


def plan_tree(low: int, high: int, counts: dict[tuple[int, int], int] | None = None) -> list[tuple[int, int, int | None, int | None]]:
    """(low, high, parent low, parent high), parents first; halves, or with ``counts`` the splits that add fewest edges."""

    @cache
    def best(i: int, j: int) -> tuple[int, int]:
        """(edges added below [i, j], where to split)."""
        if i == j:
            return 0, i
        own = alive_through(counts, i, j)
        return min((best(i, k)[0] + best(k + 1, j)[0] + alive_through(counts, i, k) + alive_through(counts, k + 1, j) - 2 * own, k) for k in range(i, j))

    out: list = [(low, high, None, None)]
    for i, j, *_ in out:
        if i < j:
            k = best(i, j)[1] if counts else (i + j) // 2
            out += [(i, k, i, j), (k + 1, j, i, j)]
    return out


def node_additions(additions: DataFrame, low: int, high: int, parent: tuple[int, int] | None) -> DataFrame:
    """Added edges alive in all of low .. high, but not in all of the parent's range."""

    def through(i: int, j: int):
        need = F.lit(True)
        for word in range(i // 64, j // 64 + 1):
            bits = ((1 << min(63, j - 64 * word) + 1) - 1) & ~((1 << max(0, i - 64 * word)) - 1)
            signed = bits - (1 << 64) if bits >> 63 else bits
            mask = F.element_at("words", F.lit(word))
            need = need & (F.coalesce(mask, F.lit(0).cast("long")).bitwiseAND(F.lit(signed).cast("long")) == signed)
        return need

    whole = additions.groupBy("src", "dst", "w").agg(F.map_from_entries(F.collect_list(F.struct("word", "mask"))).alias("words"))
    own = through(low, high)
    return whole.where(own if parent is None else own & ~through(*parent)).select("src", "dst", "w")


def run_tree(tree: list, start: DataFrame, base: DataFrame, additions: DataFrame, algebra: PathAlgebra, work: Work) -> dict[int, DataFrame]:
    """Values of each leaf; a node's values are reached once and serve both halves."""
    states = {tree[0][:2]: (start, base)}
    leaves = {}
    for low, high, *parent in tree:
        if parent[0] is not None:
            state, edges = states[tuple(parent)]
            added = addition_set(additions, low) if low == high else node_additions(additions, low, high, tuple(parent))
            if low == high:  # at a leaf all its additions count; those of its ancestors change nothing any more
                added = added.join(edges, ["src", "dst", "w"], "left_anti")
            states[low, high] = relax_additions(state, edges, added, algebra, work), edges.unionByName(added)
        if low == high:
            leaves[low] = states[low, high][0] if parent[0] is not None else relax_additions(start, base, addition_set(additions, low), algebra, work)
    return leaves


def tree_sizes(lifetimes_counts: dict[tuple[int, int], int], tree: list) -> list[tuple[int, int, int]]:
    """(low, high, edges added at the node); the root's are those alive throughout."""
    out = []
    for low, high, *parent in tree:
        own = alive_through(lifetimes_counts, low, high)
        out.append((low, high, own - (alive_through(lifetimes_counts, *parent) if parent[0] is not None else 0)))
    return out
