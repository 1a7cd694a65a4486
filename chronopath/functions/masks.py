"""Sets of snapshots as 64-bit words."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F



def n_words(snapshots: int) -> int:
    return -(-snapshots // 64)


def mask_of(born: str = "born", died: str = "died", word: str = "word") -> Column:
    """Bits of the snapshots born .. died - 1 that lie in a word."""
    low, high = f"greatest({born} - 64 * {word}, 0)", f"least({died} - 64 * {word}, 64)"
    return F.expr(f"case when {high} <= {low} then 0L else shiftleft(-1L, {low}) & shiftrightunsigned(-1L, 64 - {high}) end")


def chosen_words(chosen: Iterable[int]) -> dict[int, int]:
    """word -> mask (as signed 64 bits) of a set of snapshots."""
    out: dict[int, int] = {}
    for i in chosen:
        out[i // 64] = out.get(i // 64, 0) | 1 << i % 64
    return {k: m - (1 << 64) if m >> 63 else m for k, m in out.items()}


def word_table(spark, chosen: Iterable[int]) -> DataFrame:
    """(word, chosen): a row for each word, thus one for each 64 snapshots."""
    return spark.createDataFrame(sorted(chosen_words(chosen).items()), "word int, chosen long")


def expand(df: DataFrame, mask: str = "mask", word: str = "word") -> DataFrame:
    """A row for each set bit, with its snapshot in ``snap``."""
    bits = F.filter(F.sequence(F.lit(0), F.lit(63)), lambda i: F.call_function("bit_get", F.col(mask), i) == 1)
    return df.withColumn("_bit", F.explode(bits)).withColumn("snap", (F.col("_bit") + 64 * F.col(word)).cast("int")).drop("_bit", mask, word)
