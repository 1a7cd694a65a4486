"""Removal of word windows that repeat across documents.

A window is ``window`` consecutive words of one document; it is repeated if a
document with a smaller id has the same words in a row. Windows are compared by
Rabin-Karp hashes, counted in Spark, and repeated windows merge into maximal
intervals. Two cheap exact steps keep the shuffles small:

* documents of equal word sequences are one class; only the member with the
  smallest id takes part, the others lose every word;
* a window can repeat only if the smallest hash among its short word runs also
  occurs in another document (equal windows have equal minima). Those minima are
  few; windows whose minimum is unique are settled without being shuffled.

Edge cases: null and short texts keep all words; rows without an id keep all and
remove nothing; rows of one id never remove each other's words; repeated rows give
repeated results; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronopath.llm.common import Rolling, Scratch, WordHash, mix, slices, words

WINDOW, RUN = 50, 10

_SECOND = np.uint64(0xA0761D6478BD642F)


def sliding_min(x: np.ndarray, size: int) -> np.ndarray:
    """Minimum of each ``size`` neighbours, by doubling spans."""
    span = 1
    while span < size:
        step = min(span, size - span)
        x = np.minimum(x[:-step], x[step:]) if len(x) > step else x[:0]
        span += step
    return x


class Batch:
    """The texts of an Arrow batch as one sequence of word hashes."""

    def __init__(self, texts: list[str | None], memo: WordHash):
        self.words = [words(t) for t in texts]
        self.sizes = np.array([len(w) for w in self.words], np.int64)
        self.starts = np.concatenate([[0], np.cumsum(self.sizes)])
        self.hashes = memo.array([w for doc in self.words for w in doc])
        self.rolling = Rolling(self.hashes)

    def minima(self, window: int, run: int) -> np.ndarray:
        """At each window's start, the smallest hash of its runs."""
        return sliding_min(self.rolling.windows(run), window - run + 1)

    def of(self, k: int, window: int) -> slice:
        """Where document k's windows start."""
        return slice(self.starts[k], max(self.starts[k], self.starts[k + 1] - window + 1))


def summaries(docs: DataFrame, id_col: str, text_col: str, window: int, run: int) -> DataFrame:
    """(id, n_words, sha, prints): digest of the words, and the distinct minima of the windows."""

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        memo = WordHash()
        for batch in slices(batches):
            texts = Batch(batch.column(1).to_pylist(), memo)
            low = texts.minima(window, run).view(np.int64)
            sha = [hashlib.sha256(b" ".join(w)).hexdigest() for w in texts.words]
            prints = [np.unique(low[texts.of(k, window)]) for k in range(len(sha))]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts.sizes), pa.array(sha), pa.array(prints, pa.list_(pa.int64()))], names=["id", "n_words", "sha", "prints"])

    source = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return source.mapInArrow(go, f"id {source.schema['id'].dataType.simpleString()}, n_words long, sha string, prints array<long>")


def window_rows(candidates: DataFrame, window: int, run: int) -> DataFrame:
    """(h1, h2, id, sha, start) of the windows of (id, sha, text, shared) whose minimum is in ``shared``."""

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        memo = WordHash()
        for batch in slices(batches):
            texts = Batch(batch.column(2).to_pylist(), memo)
            low, first = texts.minima(window, run).view(np.int64), texts.rolling.windows(window)
            second = Rolling(mix(texts.hashes ^ _SECOND)).windows(window)
            at, doc = [], []
            for k, shared in enumerate(batch.column(3)):
                own = texts.of(k, window)
                hit = np.flatnonzero(np.isin(low[own], shared.values.to_numpy())) + own.start
                at.append(hit)
                doc.append(np.full(len(hit), k, np.int32))
            at, doc = np.concatenate(at), pa.array(np.concatenate(doc))
            yield pa.RecordBatch.from_arrays([pa.array(first[at].view(np.int64)), pa.array(second[at].view(np.int64).astype(np.int32)), batch.column(0).take(doc), batch.column(1).take(doc), pa.array((at - texts.starts[np.asarray(doc)]).astype(np.int32))], names=["h1", "h2", "id", "sha", "start"])

    kind = candidates.schema["id"].dataType.simpleString()
    return candidates.select("id", "sha", "text", "shared").mapInArrow(go, f"h1 long, h2 int, id {kind}, sha string, start int")


def intervals(starts: np.ndarray, window: int) -> np.ndarray:
    """Maximal [from, to) that windows at these starts cover."""
    starts = np.unique(starts)
    if not len(starts):
        return np.zeros((0, 2), np.int64)
    cut = np.flatnonzero(np.diff(starts) > window) + 1
    return np.stack([starts[np.r_[0, cut]], starts[np.r_[cut - 1, len(starts) - 1]] + window], axis=1)


def clean(hit: DataFrame, window: int) -> DataFrame:
    """(id, sha, spans, kept, n_removed, kept_sha256) of (id, sha, text, starts)."""

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            spans, kept, removed, sha = [], [], [], []
            for text, starts in zip(batch.column(2).to_pylist(), batch.column(3)):
                tokens, found = words(text), intervals(starts.values.to_numpy().astype(np.int64), window)
                edges = [0, *found.ravel().tolist(), len(tokens)]
                rest = b" ".join([w for a, b in zip(edges[::2], edges[1::2]) for w in tokens[a:b]])
                spans.append(found.tolist())
                kept.append(rest.decode("utf-8", "surrogatepass"))
                removed.append(int((found[:, 1] - found[:, 0]).sum()))
                sha.append(hashlib.sha256(rest).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(spans, pa.list_(pa.list_(pa.int64()))), pa.array(kept), pa.array(removed, pa.int64()), pa.array(sha)], names=["id", "sha", "spans", "kept", "n_removed", "kept_sha256"])

    kind = hit.schema["id"].dataType.simpleString()
    return hit.select("id", "sha", "text", "starts").mapInArrow(go, f"id {kind}, sha string, spans array<array<long>>, kept string, n_removed long, kept_sha256 string")


def repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", window: int = WINDOW, run: int = RUN) -> tuple[DataFrame, DataFrame]:
    """(summary of every row with ``copy_of`` set where a whole text repeats, cleaned rows that lose some windows)."""
    scratch = Scratch(docs.sparkSession)
    base = scratch.keep(summaries(docs, id_col, text_col, window, run), "summaries")
    eligible = base.where((F.col("n_words") >= window) & F.col("id").isNotNull())
    classes = eligible.groupBy("sha").agg(F.min("id").alias("first"))
    prints = eligible.join(classes, "sha").where("id = first").dropDuplicates(["id", "sha"]).select("id", "sha", F.explode("prints").alias("print"))
    prints = scratch.keep(prints, "prints")
    common = scratch.keep(prints.groupBy("print").agg(F.min("id").alias("a"), F.max("id").alias("b")).where("a < b").select("print"), "common")
    shared = prints.join(common.hint("merge"), "print").groupBy("id", "sha").agg(F.collect_list("print").alias("shared"))
    texts = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    candidates = texts.join(shared, "id").where(F.sha2(F.array_join(F.filter(F.split("text", "[\\x20\\x09-\\x0D]+"), lambda w: w != ""), " "), 256) == F.col("sha")).dropDuplicates(["id", "sha"])
    candidates = scratch.keep(candidates, "candidates")
    found = window_rows(candidates, window, run)
    least = found.groupBy("h1", "h2").agg(F.min("id").alias("first"), F.max("id").alias("last")).where("first < last").drop("last")
    least = scratch.keep(least, "least")  # apart from the join, so that a window of very many rows can be split there
    starts = found.join(least.hint("merge"), ["h1", "h2"]).where("id > first").groupBy("id", "sha").agg(F.collect_list("start").alias("starts"))
    cleaned = scratch.keep(clean(candidates.drop("shared").join(starts, ["id", "sha"]), window), "cleaned")
    scratch.drop(prints, candidates, common, least)
    copies = base.drop("prints").join(classes.where(F.col("first").isNotNull()), "sha", "left").withColumn("copy_of", F.when((F.col("n_words") >= window) & (F.col("id") > F.col("first")), F.col("first"))).drop("first")
    return copies, cleaned


def digest(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", window: int = WINDOW) -> DataFrame:
    """Per row: n_words, n_removed and the SHA-256 of the kept words joined by spaces."""
    copies, cleaned = repeats(docs, id_col, text_col, window)
    out = copies.join(cleaned.select("id", "sha", F.col("n_removed").alias("some"), F.col("kept_sha256").alias("rest")), ["id", "sha"], "left")
    whole = F.col("copy_of").isNotNull()
    return out.select(F.col("id").alias(id_col), "n_words", F.when(whole, F.col("n_words")).otherwise(F.coalesce("some", F.lit(0))).alias("n_removed"), F.when(whole, F.lit(hashlib.sha256().hexdigest())).otherwise(F.coalesce("rest", "sha")).alias("kept_sha256"))


def remove(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", window: int = WINDOW) -> DataFrame:
    """(id, kept): texts of the rows that change; words joined by single spaces."""
    copies, cleaned = repeats(docs, id_col, text_col, window)
    return copies.where("copy_of is not null").select(F.col("id").alias(id_col), F.lit("").alias("kept")).unionByName(cleaned.select(F.col("id").alias(id_col), "kept"))


def op8_substrings(spark, sf_dir: str) -> DataFrame:
    return digest(spark.read.parquet(f"{sf_dir}/documents.parquet"))


OP8_SQL = f"""
WITH w AS (
  SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS ws FROM documents
), places AS (SELECT doc_id, ws, unnest(range(1, len(ws) + 1)) AS i FROM w),
windows AS (SELECT doc_id, i, array_to_string(ws[i : i + {WINDOW - 1}], ' ') AS g FROM places WHERE i + {WINDOW - 1} <= len(ws)),
earliest AS (SELECT g, min(doc_id) AS d FROM windows GROUP BY g),
hits AS (SELECT doc_id, i FROM windows JOIN earliest USING (g) WHERE d < doc_id),
gone AS (SELECT DISTINCT doc_id, i + k AS i FROM hits, range({WINDOW}) AS t(k)),
kept AS (
  SELECT p.doc_id, count(g.i) AS n_removed, string_agg(CASE WHEN g.i IS NULL THEN p.ws[p.i] END, ' ' ORDER BY p.i) AS rest
  FROM places p LEFT JOIN gone g ON p.doc_id = g.doc_id AND p.i = g.i GROUP BY p.doc_id
)
SELECT w.doc_id, len(ws)::BIGINT AS n_words, coalesce(n_removed, 0)::BIGINT AS n_removed, sha256(coalesce(rest, '')) AS kept_sha256
FROM w LEFT JOIN kept USING (doc_id)
"""
