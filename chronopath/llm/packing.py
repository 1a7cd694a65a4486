"""Best-fit packing by minimum bin slack.

Documents are encoded, closed by id 0 and cut only where longer than a sequence.
A bin takes the largest piece left; a bitset subset-sum over the lengths still
available finds the fullest completion. Taking that combination away leaves the
same choice fullest, so it is repeated until one of its lengths runs short: the
plan depends on the histogram of lengths alone (at most ``capacity`` entries) and
needs a number of steps bounded by the capacity, however many documents there are.
Pieces then find their place by their rank among pieces of equal length; ranks
are counted in salted groups, so a length that a third of all pieces share is
spread over many tasks.

Edge cases: a null or empty text is the single id 0; a piece as long as a
sequence fills one alone; repeated rows are packed each on their own; a null id
is carried through; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import itertools
import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from chronopath.llm.common import Scratch, bpe, give_back, slices

CAPACITY = 2048
#: Pieces of one length ranked together by one task.
RANKED_TOGETHER = 100_000
PIECES = "piece int, start long, length long, ids_crc32 long"


def cut(n: int, capacity: int) -> list[tuple[int, int]]:
    """(start, length) of the pieces of a document of n ids; only the first may be short."""
    head = n % capacity or capacity
    return [(0, head)] + [(s, capacity) for s in range(head, n, capacity)]


def encode_pieces(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", capacity: int = CAPACITY, vocabulary: str | None = None) -> DataFrame:
    """A row for each piece of each document, with the CRC-32 of its packed ids."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = bpe(vocabulary)
        for batch in slices(batches):
            rows: list[list] = [[], [], [], [], []]
            found, starts = encoder.column(batch.column(1))
            for key, (low, high) in zip(batch.column(0).to_pylist(), itertools.pairwise(starts.tolist())):
                ids = found[low:high].tobytes() + b"\0\0\0\0"
                for k, (start, length) in enumerate(cut(len(ids) // 4, capacity)):
                    for column, value in zip(rows, (key, k, start, length, zlib.crc32(ids[4 * start : 4 * (start + length)]))):
                        column.append(value)
            yield pa.RecordBatch.from_arrays([pa.array(rows[0], batch.schema.field(0).type), pa.array(rows[1], pa.int32()), *(pa.array(x, pa.int64()) for x in rows[2:])], names=["id", "piece", "start", "length", "ids_crc32"])
        give_back()

    source = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return source.mapInArrow(run, f"id {source.schema['id'].dataType.simpleString()}, {PIECES}").withColumnRenamed("id", id_col)


def fullest(available: list[tuple[int, int]], room: int) -> dict[int, int]:
    """The multiset of lengths, out of (length, count) in falling order, with the largest sum <= room."""
    reach, limit, steps = 1, (1 << (room + 1)) - 1, []
    for length, count in available:
        left, part = min(count, room // length), 1
        while left > 0 and not reach >> room & 1:
            part = min(part, left)
            steps.append((length, part, reach))
            reach |= reach << (length * part) & limit
            left, part = left - part, part * 2
        if reach >> room & 1:
            break
    at, chosen = reach.bit_length() - 1, Counter()
    for length, part, before in reversed(steps):
        if not before >> at & 1:
            chosen[length] += part
            at -= length * part
    return dict(chosen)


def plan(histogram: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, dict[int, int]]]:
    """(number of bins, lengths in each) until no piece is left."""
    left, bins = {k: v for k, v in histogram.items() if v > 0}, []
    while left:
        seed = max(left)
        rest = [(k, v - (k == seed)) for k, v in sorted(left.items(), reverse=True)]
        room = capacity - seed
        combo = Counter(fullest([(k, v) for k, v in rest if v and k <= room], room)) if room else Counter()
        combo[seed] += 1
        times = min(left[k] // n for k, n in combo.items())
        bins.append((times, dict(combo)))
        for k, n in combo.items():
            left[k] -= n * times
            if not left[k]:
                del left[k]
    return bins


def _slots(bins: list[tuple[int, dict[int, int]]]) -> np.ndarray:
    """Columns (length, first rank, first bin, pieces of that length in a bin, offset of their first), sorted."""
    out, base, used = [], 0, Counter()
    for times, combo in bins:
        offset = 0
        for length in sorted(combo, reverse=True):
            out.append((length, used[length], base, combo[length], offset))
            used[length] += times * combo[length]
            offset += length * combo[length]
        base += times
    return np.array(sorted(out), dtype=np.int64).reshape(-1, 5)


def place(pieces: DataFrame, id_col: str = "doc_id", capacity: int = CAPACITY) -> DataFrame:
    """Give each piece of a stored table its sequence and its offset there."""
    histogram = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}
    slots = _slots(plan(histogram, capacity))
    salts = max(1, -(-max(histogram.values(), default=0) // RANKED_TOGETHER))
    salted = pieces.withColumn("salt", F.pmod(F.xxhash64(id_col, "piece", "ids_crc32"), F.lit(salts)))
    before = salted.groupBy("length", "salt").agg(F.count("*").alias("n")).withColumn("before", F.coalesce(F.sum("n").over(Window.partitionBy("length").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("n")
    rank = F.row_number().over(Window.partitionBy("length", "salt").orderBy(id_col, "piece", "start", "ids_crc32")) - 1
    ranked = salted.withColumn("rank", rank).join(before, ["length", "salt"]).withColumn("rank", F.col("rank") + F.col("before"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            length, rank = (np.asarray(batch.column(i), dtype=np.int64) for i in (3, 5))
            low, high = np.searchsorted(slots[:, 0], length, "left"), np.searchsorted(slots[:, 0], length, "right")
            while (low + 1 < high).any():  # the last slot of this length that starts at or before the rank
                mid = (low + high) // 2
                take = slots[np.minimum(mid, len(slots) - 1), 1] <= rank
                low, high = np.where((low + 1 < high) & take, mid, low), np.where((low + 1 < high) & ~take, mid, high)
            found = slots[low]
            inside = rank - found[:, 1]
            yield pa.RecordBatch.from_arrays([*batch.columns[:5], pa.array(found[:, 2] + inside // found[:, 3]), pa.array(found[:, 4] + inside % found[:, 3] * length)], names=[*batch.schema.names[:5], "sequence_id", "offset"])

    kind = pieces.schema[id_col].dataType.simpleString()
    return ranked.select(F.col(id_col).alias("id"), "piece", "start", "length", "ids_crc32", "rank").mapInArrow(run, f"id {kind}, {PIECES}, sequence_id long, offset long").withColumnRenamed("id", id_col)


def pack(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", capacity: int = CAPACITY, vocabulary: str | None = None) -> DataFrame:
    """Pieces of all documents with ``sequence_id`` and gapless ``offset``."""
    stored = Scratch(docs.sparkSession).keep(encode_pieces(docs, id_col, text_col, capacity, vocabulary), "pieces")
    return place(stored, id_col, capacity)


def op3_pack(spark, sf_dir: str) -> DataFrame:
    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet"))
