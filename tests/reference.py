"""An independent best-first solver on plain Python graphs, and small graphs with known answers."""

import heapq
import itertools
import random

EXTEND = {"hops": lambda a, w: a + 1, "shortest": lambda a, w: a + w, "widest": min, "narrowest": max, "likeliest": lambda a, w: a / w}
LIFETIMES = "src long, dst long, w double, born int, died int"


def solve(lives, snap, source, algebra):
    out = {}
    for a, b, w, born, died in lives:
        if born <= snap < died:
            out.setdefault(a, []).append((b, w))
    sign = 1 if algebra.direction == "min" else -1
    best, queue = {source: algebra.source_value}, [(sign * algebra.source_value, source)]
    while queue:
        cost, v = heapq.heappop(queue)
        if cost != sign * best[v]:
            continue
        for b, w in out.get(v, []):
            value = EXTEND[algebra.name](best[v], w)
            if b not in best or sign * value < sign * best[b]:
                best[b] = value
                heapq.heappush(queue, (sign * value, b))
    return best


def everywhere(lives, snapshots, source, algebra):
    return {(v, i): x for i in snapshots for v, x in solve(lives, i, source, algebra).items()}


NAMES = {c: i for i, c in enumerate("sabxdrcpqy")}


def two_snapshots():
    """Two snapshots; vertex c keeps its value by two different paths and cannot be settled."""
    shared = [("s", "a", 3), ("s", "b", 4), ("s", "x", 1), ("s", "d", 3), ("s", "r", 2), ("a", "c", 8), ("d", "p", 2), ("p", "q", 1), ("p", "y", 3)]
    first, second = [("x", "d", 1), ("b", "c", 6), ("d", "r", 9)], [("d", "c", 7), ("s", "y", 5)]
    rows = [(e, 0, 2) for e in shared] + [(e, 0, 1) for e in first] + [(e, 1, 2) for e in second]
    return [(NAMES[a], NAMES[b], float(w), i, j) for (a, b, w), i, j in rows]


def four_snapshots():
    edges = [(0, 1, 2, "1111"), (0, 2, 5, "1111"), (2, 3, 1, "1111"), (1, 2, 1, "0011"), (1, 3, 9, "1000"), (3, 4, 1, "0101")]
    return [(a, b, float(w), i, i + 1) for a, b, w, mask in edges for i in range(4) if mask[3 - i] == "1"]


def random_lives(seed, vertices=18, snapshots=4, density=0.15):
    """Edges that stay, come, go, or go and return with another weight."""
    rng, rows = random.Random(seed), []
    for a, b in itertools.product(range(vertices), range(vertices)):
        if a != b and rng.random() < density:
            kind, w, step = rng.random(), float(rng.randint(1, 9)), rng.randint(1, snapshots - 1)
            if kind < 0.6:
                rows.append((a, b, w, 0, snapshots))
            elif kind < 0.75:
                rows.append((a, b, w, step, snapshots))
            elif kind < 0.9:
                rows.append((a, b, w, 0, step))
            else:
                rows += [(a, b, w, 0, 1), (a, b, float(rng.randint(1, 9)), 2, snapshots)]
    return rows
