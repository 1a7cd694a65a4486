"""From raw documents to packed sequences, in five stages.

Each stage takes the rows its predecessor kept, with the columns of ``documents``
(and any others, untouched), and is written as Parquet before the next one reads
it. Rows without an id pass every filter; an empty table passes through.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chronopath.llm import decontaminate, jaccard, linechunks, packing, toxicity
from chronopath.llm.common import Scratch

#: Documents that score at least this much are rejected as toxic. Stricter than the operator's 0.3: see README.
TOXIC = 0.5


def _without(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """``docs`` but for those whose id is listed, by a shuffle at every size."""
    return docs.join(ids.distinct().hint("shuffle_hash"), "doc_id", "left_anti").select(docs.columns)


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Learn toxicity from the labels of these documents, and drop those that score as toxic."""
    model = toxicity.fit_tables(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    scored = toxicity.score(docs, model, prefix="_toxicity_")
    return scored.where(F.col("_toxicity_score") < TOXIC).select(docs.columns)


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cut repeated chunks of lines; a document that loses all it had goes."""
    cut = linechunks.remove(docs.withColumnRenamed("lines_removed", "_own_lines_removed"))
    changed = F.col("lines_removed") > 0
    if "n_chars" in docs.columns:
        cut = cut.withColumn("n_chars", F.when(changed, F.char_length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))
    return cut.where(~changed | F.col("text").rlike("[^ \\t-\\r]")).drop("lines_removed").withColumnRenamed("_own_lines_removed", "lines_removed").select(docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group linked by near equality (five words, 0.8), the smallest id stays."""
    groups = Scratch(spark).keep(jaccard.near_duplicates(docs, size=5, threshold=(80, 100)), "groups")
    return _without(docs, groups.where("component_id < doc_id").select("doc_id"))


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents that hold a benchmark item."""
    found = Scratch(spark).keep(decontaminate.contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")), "contaminated")
    return _without(docs, found.where("doc_id is not null").select("doc_id"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Encode and pack what is left."""
    return packing.pack(docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("line_dedup", drop_repeated_lines),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("packing", pack),
]

#: Model scores and token ids are beyond SQL; tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = Scratch(spark).keep(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
