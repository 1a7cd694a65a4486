"""Functions for SQL users: mask bits as a table function, and a reference solver for one small graph a group."""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from chronopath.functions.algebra import PathAlgebra


@udtf(returnType="snap: int")
class MaskToSnapshots:
    def eval(self, mask: int, word: int):
        for i in range(64):
            if mask is not None and mask >> i & 1:
                yield (64 * word + i,)


def register(spark: SparkSession) -> None:
    spark.udtf.register("mask_to_snapshots", MaskToSnapshots)


def local_finish(rows: DataFrame, algebra: PathAlgebra, source: int, starts: DataFrame | None = None) -> DataFrame:
    """(v, snap, val) from (snap, src, dst, w), each snapshot solved best-first in one task.

    For residual graphs that fit a task, and as an independent check of the loops. ``starts`` (snap, v, val) are values
    known to begin with, instead of the source's; edges of a task are held as arrays of numbers, 24 bytes each."""
    name, sign, start = algebra.name, 1 if algebra.direction == "min" else -1, algebra.source_value
    extend = {"hops": lambda a, w: a + 1, "shortest": lambda a, w: a + w, "widest": min, "narrowest": max, "likeliest": lambda a, w: a / w}[name]
    given = starts is not None

    def solve(group: pa.Table) -> pa.Table:
        src, dst, w = (group.column(c).combine_chunks() for c in ("src", "dst", "w"))
        first = np.asarray(pc.is_null(src))  # rows of starts
        src, dst, w = (np.asarray(x) for x in (pc.fill_null(src, 0), dst, w))
        known = zip(dst[first].tolist(), w[first].tolist()) if given else [(source, start)]
        best: dict[int, float] = {}
        for v, value in known:
            if v not in best or sign * value < sign * best[v]:
                best[v] = value
        order = np.flatnonzero(~first)
        order = order[np.argsort(src[order], kind="stable")]
        src, dst, w = src[order], dst[order], w[order]
        begins = np.flatnonzero(np.concatenate([[True], src[1:] != src[:-1]])[: len(src)])
        heads = src[begins]
        ends = np.append(begins[1:], len(src))
        queue = [(sign * value, v) for v, value in best.items()]
        heapq.heapify(queue)
        while queue:
            cost, v = heapq.heappop(queue)
            at = int(np.searchsorted(heads, v)) if cost == sign * best[v] else len(heads)
            if at < len(heads) and heads[at] == v:
                for b, x in zip(dst[begins[at] : ends[at]].tolist(), w[begins[at] : ends[at]].tolist()):
                    value = extend(best[v], x)
                    if b not in best or sign * value < sign * best[b]:
                        best[b] = value
                        heapq.heappush(queue, (sign * value, b))
        snap = group.column("snap")[0].as_py()
        return pa.table({"v": pa.array(best.keys(), pa.int64()), "snap": pa.array([snap] * len(best), pa.int32()), "val": pa.array(best.values(), pa.float64())})

    edges = rows.select("snap", "src", "dst", F.col("w").cast("double").alias("w"))
    if given:
        edges = edges.unionByName(starts.select("snap", F.lit(None).cast("long").alias("src"), F.col("v").alias("dst"), F.col("val").alias("w")))
    return edges.groupBy("snap").applyInArrow(solve, "v long, snap int, val double")
