"""Which snapshots, in what mode and with which strategy."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass


@dataclass(frozen=True)
class Step:
    name: str
    snapshots: tuple[int, ...]


def schedule(chosen: Iterable[int], strategy: str) -> list[Step]:
    """The steps of a strategy over the chosen snapshots, in order."""
    wanted = tuple(sorted(set(chosen)))
    if strategy == "recompute":
        return [Step("full", (i,)) for i in wanted]
    if strategy == "stream_inc":
        return [Step("full", wanted[:1])] + [Step("batch", (i,)) for i in wanted[1:]]
    generation = [Step("core", wanted)] + ([Step("hull", wanted), Step("reduce", wanted)] if strategy.startswith("residual") else [])
    if strategy.endswith(("conc", "shared")) and not strategy.endswith("share"):
        return [*generation, Step("concurrent", wanted)]
    if strategy.endswith("share"):
        return [*generation, Step("tree", wanted)]
    return generation + [Step("additions", (i,)) for i in wanted]


def reusable(cached: Iterable[int], wanted: Iterable[int]) -> bool:
    """Core values of a window start any part of it: its core has no edge that a part's core lacks."""
    return set(wanted) <= set(cached)


@dataclass(frozen=True)
class Counts:
    core_edges: int
    added_edges: int
    vertices: int
    unstable: int
    snapshots: int


def choose(counts: Counts) -> str:
    """Strategy by counts known after the bounds: reduction pays while most vertices are stable."""
    if counts.snapshots == 1:
        return "recompute"
    return "residual_conc" if counts.unstable <= 0.7 * counts.vertices else "core_conc"


def residual_mode(unstable: int, vertices: int) -> str:
    """Build the residual graph up from unstable vertices, or take edges into stable ones away."""
    return "semi" if 2 * unstable < vertices else "anti"


def traversal(frontier: int, unstable: int) -> str:
    """Push from a small frontier; pull into the unstable vertices when most of them are active."""
    return "pull" if frontier > 0.5 * max(1, unstable) else "push"
