"""Fixed schemas of the engine's tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql.types import DoubleType, IntegerType, LongType, StringType, StructField, StructType


def _schema(**fields) -> StructType:
    return StructType([StructField(name, kind()) for name, kind in fields.items()])


EDGES = _schema(src=LongType, dst=LongType, w=DoubleType)
#: Alive in snapshots born .. died - 1; lives of one pair do not overlap.
LIFETIMES = _schema(src=LongType, dst=LongType, w=DoubleType, born=IntegerType, died=IntegerType)
BATCHES = _schema(step=IntegerType, op=StringType, src=LongType, dst=LongType, w=DoubleType)
#: Bit i % 64 of word i / 64 stands for snapshot i.
VERSIONED = _schema(src=LongType, dst=LongType, w=DoubleType, word=IntegerType, mask=LongType)
STATE = _schema(v=LongType, val=DoubleType)
MASKED_STATE = _schema(v=LongType, val=DoubleType, word=IntegerType, mask=LongType)
RESULTS = _schema(v=LongType, snap=IntegerType, val=DoubleType)


def require(df: DataFrame, schema: StructType) -> DataFrame:
    """The schema's columns of ``df``, cast to its types; an error names what is missing."""
    missing = [f.name for f in schema if f.name not in df.columns]
    if missing:
        raise ValueError(f"missing columns: {', '.join(missing)}")
    return df.select(*(df[f.name].cast(f.dataType).alias(f.name) for f in schema))
