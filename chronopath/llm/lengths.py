"""Exact histogram of encoded lengths.

One pass encodes every text; a row for each distinct length carries how many
documents have it, and suffix sums over falling lengths answer, for any context
limit, how many documents reach it and how many tokens remain after truncation.
The suffix sums run inside blocks of lengths and over block totals, so no single
task sees the whole histogram.

Edge cases: a null or empty text has length 0 and is counted; repeated rows count
each; an empty table gives no rows; ids and other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from chronopath.llm.common import Scratch, bpe, slices

BLOCK = 512


def encoded_lengths(docs: DataFrame, text_col: str = "text", vocabulary: str | None = None) -> DataFrame:
    """(length, n) as each task found them; not yet added up."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = bpe(vocabulary)
        for batch in slices(batches):
            length, n = np.unique(np.diff(encoder.column(batch.column(0))[1]), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(length), pa.array(n.astype(np.int64))], names=["length", "n"])

    return docs.select(F.col(text_col).cast("string").alias("text")).mapInArrow(run, "length long, n long")


def histogram(docs: DataFrame, text_col: str = "text", vocabulary: str | None = None) -> DataFrame:
    """Per distinct length L: n_docs and n_tokens of exactly L, docs_reaching and
    tokens_reaching (length >= L), truncated_tokens (sum of min(length, L)),
    total_docs, total_tokens and share_within (documents of at most L)."""
    counted = encoded_lengths(docs, text_col, vocabulary).groupBy("length").agg(F.sum("n").alias("n_docs"))
    by_length = Scratch(docs.sparkSession).keep(counted, "lengths")  # read twice below; texts are encoded once
    by_length = by_length.withColumn("n_tokens", F.col("length") * F.col("n_docs")).withColumn("block", F.floor(F.col("length") / BLOCK))
    after = Window.orderBy(F.desc("block")).rowsBetween(Window.unboundedPreceding, -1)
    every = Window.orderBy(F.desc("block")).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    blocks = by_length.groupBy("block").agg(F.sum("n_docs").alias("d"), F.sum("n_tokens").alias("t"))
    blocks = blocks.select("block", F.coalesce(F.sum("d").over(after), F.lit(0)).alias("d_after"), F.coalesce(F.sum("t").over(after), F.lit(0)).alias("t_after"), F.sum("d").over(every).alias("total_docs"), F.sum("t").over(every).alias("total_tokens"))
    inside = Window.partitionBy("block").orderBy(F.desc("length")).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    out = by_length.join(blocks, "block").withColumn("docs_reaching", F.sum("n_docs").over(inside) + F.col("d_after")).withColumn("tokens_reaching", F.sum("n_tokens").over(inside) + F.col("t_after"))
    return out.select(
        "length", "n_docs", "n_tokens", "docs_reaching", "tokens_reaching",
        (F.col("total_tokens") - F.col("tokens_reaching") + F.col("length") * F.col("docs_reaching")).alias("truncated_tokens"),
        "total_docs", "total_tokens",
        (1 - (F.col("docs_reaching") - F.col("n_docs")) / F.col("total_docs")).alias("share_within"),
    )


def at_limit(hist: DataFrame, limit: int) -> DataFrame:
    """One row for any context limit: documents longer than it, tokens kept and lost by truncation."""
    kept = F.sum(F.least("length", F.lit(limit)) * F.col("n_docs"))
    return hist.agg(F.lit(limit).alias("context"), F.coalesce(F.sum(F.when(F.col("length") > limit, F.col("n_docs"))), F.lit(0)).alias("docs_cut"), F.coalesce(kept, F.lit(0)).alias("tokens_kept"), F.coalesce(F.sum("n_tokens") - kept, F.lit(0)).alias("tokens_lost"))


def quantile(hist: DataFrame, q: float) -> DataFrame:
    """The smallest length that at least a share q of the documents do not exceed (null on no documents)."""
    return hist.where(F.col("share_within") >= q).agg(F.min("length").alias("length"))


def op5_lengths(spark, sf_dir: str) -> DataFrame:
    return histogram(spark.read.parquet(f"{sf_dir}/documents.parquet"))
