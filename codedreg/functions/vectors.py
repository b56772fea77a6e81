"""Array expressions and a distributed vector sum."""

from __future__ import annotations

from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.ml.stat import Summarizer
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def dot(a: str | Column, b: str | Column) -> Column:
    """Inner product of two arrays of one size."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda acc, x: acc + x)


def norm2(a: str | Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda acc, x: acc + x * x)


def literal(values) -> Column:
    return F.array(*[F.lit(float(v)) for v in values])


def sum_vectors(df: DataFrame, keys: list[str], columns: list[str]) -> DataFrame:
    """Element-wise sums of array columns by key, combined on the map side before the one shuffle."""
    sums = [vector_to_array(Summarizer.sum(array_to_vector(c))).alias(c) for c in columns]
    return (df.groupBy(*keys) if keys else df).agg(*sums)


def long_form(df: DataFrame, keys: list[str], column: str = "x") -> DataFrame:
    """keys, j (from 0), v: for small results only."""
    return df.select(*keys, F.posexplode(column).alias("j", "v"))


def rounded(column: str | Column, digits: int = 6) -> Column:
    """Rounded, with one kind of zero."""
    return F.round(column, digits) + F.lit(0.0)
