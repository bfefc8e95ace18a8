"""The vector column: a list of floats with a declared dimension, checked and never inferred."""

from __future__ import annotations

import math
from collections.abc import Iterable
from dataclasses import dataclass
from decimal import Decimal

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


class DimensionMismatch(ValueError):
    """A vector of another length than declared; a wrong query must fail, not find nothing."""


@dataclass(frozen=True)
class VectorSpec:
    column: str
    dim: int
    metric: str = "l2"

    def __post_init__(self):
        if self.dim < 1 or self.metric != "l2":
            raise ValueError("a vector needs a positive dimension; the indexed metric is l2")


def validate(df: DataFrame, spec: VectorSpec) -> DataFrame:
    """df with every vector checked as it is read: null is allowed, another length is an error."""
    kind = df.schema[spec.column].dataType
    if not isinstance(kind, T.ArrayType) or not isinstance(kind.elementType, (T.FloatType, T.DoubleType, T.DecimalType)):
        raise DimensionMismatch(f"{spec.column} is {kind.simpleString()}, not a list of numbers")
    vector = F.col(spec.column)
    wrong = F.raise_error(F.concat(F.lit(f"{spec.column}: dimension "), F.size(vector).cast("string"), F.lit(f", declared {spec.dim}")))
    checked = F.when(vector.isNull() | (F.size(vector) == spec.dim), vector.cast("array<float>")).otherwise(wrong.cast("array<float>"))
    return df.withColumn(spec.column, checked)


def coerce_query(q: Iterable, spec: VectorSpec) -> list[float]:
    """A query as doubles; decimals (what SQL makes of number literals) are cast."""
    if q is None:
        raise DimensionMismatch("the query vector is null")
    out = [float(x) if isinstance(x, (int, float, Decimal)) or hasattr(x, "__float__") else float("nan") for x in q]
    if len(out) != spec.dim:
        raise DimensionMismatch(f"the query has {len(out)} parts, {spec.column} has {spec.dim}")
    if not all(map(math.isfinite, out)):
        raise DimensionMismatch("the query holds parts that are not finite numbers")
    return out
