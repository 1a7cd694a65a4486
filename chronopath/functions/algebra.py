"""Path algebras: how an edge extends a value, and which of two values is kept.

Extending never improves a value and keeps the order of values, so relaxation in
any order ends at the best value over all paths. Values are doubles; addition,
division, minimum and maximum are monotone after rounding, so the end is unique
and bounds may be compared exactly.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class PathAlgebra:
    name: str
    extend: Callable[[Column, Column], Column]
    extend_sql: str  # the same over {val} and {w}, for SQL twins
    direction: str  # 'min' or 'max': the better value
    source_value: float
    weight_improves: str = "smaller"  # which weight makes a path better: 'smaller', 'larger' or 'none'
    weight_check: str = "w >= 0"

    def keep(self, value: Column) -> Column:
        return F.min(value) if self.direction == "min" else F.max(value)

    def better(self, new: Column, old: Column) -> Column:
        return new < old if self.direction == "min" else new > old

    def cost(self, value: Column) -> Column:
        """A number that is smaller for better values."""
        return value if self.direction == "min" else -value

    def best_weight(self, w: Column) -> Column:
        return F.max(w) if self.weight_improves == "larger" else F.min(w)

    def worst_weight(self, w: Column) -> Column:
        return F.min(w) if self.weight_improves == "larger" else F.max(w)

    def weight_better(self, new: Column, old: Column) -> Column:
        return new > old if self.weight_improves == "larger" else new < old if self.weight_improves == "smaller" else F.lit(False)

    def checked(self, edges: DataFrame) -> DataFrame:
        """``edges``, with an error at run time where a weight breaks the contract."""
        message = F.lit(f"{self.name}: weights must satisfy {self.weight_check}")
        return edges.withColumn("w", F.when(F.expr(self.weight_check), F.col("w")).otherwise(F.raise_error(message).cast("double")))


HOPS = PathAlgebra("hops", lambda val, w: val + 1, "{val} + 1", "min", 0.0, "none", "true")
SHORTEST = PathAlgebra("shortest", lambda val, w: val + w, "{val} + {w}", "min", 0.0)
WIDEST = PathAlgebra("widest", lambda val, w: F.least(val, w), "least({val}, {w})", "max", float("inf"), "larger", "w > 0")
NARROWEST = PathAlgebra("narrowest", lambda val, w: F.greatest(val, w), "greatest({val}, {w})", "min", 0.0)
LIKELIEST = PathAlgebra("likeliest", lambda val, w: val / w, "{val} / {w}", "max", 1.0, "smaller", "w >= 1")
#: The likeliest path as a sum of logarithms, for long paths whose quotient would vanish.
LIKELIEST_LOG = PathAlgebra("likeliest_log", lambda val, w: val + F.log(w), "{val} + ln({w})", "min", 0.0, "smaller", "w >= 1")

ALGEBRAS = {a.name: a for a in (HOPS, SHORTEST, WIDEST, NARROWEST, LIKELIEST)}
