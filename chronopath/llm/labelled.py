"""Labelled rows for the two scorers, and how scores are attached to documents."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from chronopath.llm.common import slices

#: Label tables of at most so many rows (about 16 bytes each) are broadcast; larger ones are joined by a shuffle.
BROADCAST_LABELS = 2_000_000


def fold(id_col: str | Column, n: int) -> Column:
    """crc32 of the id as text, modulo n; -1 for a null id."""
    col = F.col(id_col) if isinstance(id_col, str) else id_col
    return F.coalesce(F.crc32(col.cast("string").cast("binary")) % n, F.lit(-1))


def attach(docs: DataFrame, labels: DataFrame, label_col: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, text, label 0/1) of documents with a label; of several labels of one id the largest counts."""
    known = labels.where(F.col(label_col).isNotNull() & F.col(id_col).isNotNull()).groupBy(F.col(id_col).alias("id")).agg(F.max(F.col(label_col).cast("int")).alias("label"))
    if labels.count() <= BROADCAST_LABELS:
        known = F.broadcast(known)
    return docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")).join(known, "id")


def sample(labelled: DataFrame, rows: int, id_col: str = "id") -> DataFrame:
    """All rows if there are at most ``rows``, else about that many: those whose id's hash is small."""
    n, parts = labelled.count(), 1 << 20
    return labelled if n <= rows else labelled.where(F.pmod(F.xxhash64(F.lit("sample"), F.col(id_col).cast("string")), F.lit(parts)) < rows * parts // n)


def add_scores(docs: DataFrame, text_col: str, out: dict[str, str], scorer: Callable[[], Callable[[list], list[np.ndarray]]]) -> DataFrame:
    """Append the columns ``out`` (name -> type) that ``scorer()`` computes from texts; same-named columns give way."""
    kept = docs.drop(*out)
    at = kept.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        score = scorer()
        for batch in slices(batches, text_col):
            found = score(batch.column(at).to_pylist())
            yield pa.RecordBatch.from_arrays([*batch.columns, *map(pa.array, found)], names=[*batch.schema.names, *out])

    schema = StructType(list(kept.schema))
    for name, kind in out.items():
        schema = schema.add(name, kind)
    return kept.mapInArrow(run, schema)


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2, rounds: int = 60) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(mean, scale, weights with bias first) of a ridge logistic fit by Newton steps."""
    mean, scale = x.mean(axis=0), x.std(axis=0) + 1e-9
    z = np.c_[np.ones(len(x)), (x - mean) / scale]
    w, penalty = np.zeros(z.shape[1]), ridge * np.r_[0.0, np.ones(x.shape[1])] + 1e-9
    for _ in range(rounds):
        p = sigmoid(z @ w)
        step = np.linalg.solve((z * (p * (1 - p))[:, None]).T @ z + np.diag(penalty), z.T @ (p - y) + penalty * w)
        w -= step / max(1.0, np.abs(step).max() / 2)
        if np.abs(step).max() < 1e-8:
            break
    return mean, scale, w


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))
