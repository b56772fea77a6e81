"""Privacy budget of the coded tables, and its inverses."""

from __future__ import annotations

import math

from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.ml.stat import Summarizer
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def budget_bits(c, h2, sigma) -> Column:
    """Half the binary logarithm of 1 + c / (h2 + sigma^2); infinite without any cover."""
    cover = F.lit(h2) if not isinstance(h2, Column) else h2
    cover = cover + F.pow(F.lit(sigma) if not isinstance(sigma, Column) else sigma, 2)
    c = F.lit(c) if not isinstance(c, Column) else c
    return F.when(cover > 0, 0.5 * F.log2(1 + c / F.when(cover > 0, cover))).otherwise(F.lit(float("inf")))


def cover_by_client(ex: DataFrame) -> DataFrame:
    """client, l, h2: over columns, the least sum of squares after taking away the largest one; one aggregate.

    A client of a single row has h2 = 0: without noise nothing covers it.
    """
    summary = Summarizer.metrics("normL2", "max", "min", "count").summary(array_to_vector("x"))
    stats = ex.groupBy("client").agg(summary.alias("s"))
    part = lambda name: vector_to_array(f"s.{name}")
    largest = F.zip_with(part("max"), part("min"), lambda a, b: F.greatest(a * a, b * b))
    rest = F.zip_with(F.transform(part("normL2"), lambda v: v * v), largest, lambda a, b: F.greatest(a - b, F.lit(0.0)))
    # what is left by rounding alone counts as nothing
    h2 = F.when(F.col("s.count") > 1, F.array_min(rest)).otherwise(0.0)
    return stats.select("client", F.col("s.count").alias("l"), h2.alias("h2"))


def privacy_budget(ex: DataFrame, c: int, sigma: float) -> DataFrame:
    """client, h2, eps_bits."""
    return cover_by_client(ex).select("client", "h2", budget_bits(float(c), F.col("h2"), float(sigma)).alias("eps_bits"))


def overall(budget: DataFrame) -> DataFrame:
    """The budget of the whole: the largest of any client, and whose it is."""
    return budget.agg(F.max(F.struct("eps_bits", "client")).alias("m")).select("m.eps_bits", "m.client")


def sigma_for_budget(cover: DataFrame, c: int, eps_bits: float) -> DataFrame:
    """client, sigma: the least noise that keeps the budget; the largest of them serves all."""
    room = F.lit(float(c) / (4.0**eps_bits - 1)) - F.col("h2")
    return cover.select("client", F.sqrt(F.greatest(room, F.lit(0.0))).alias("sigma"))


def coded_rows_for_budget(cover: DataFrame, eps_bits: float, sigma: float) -> DataFrame:
    """client, coded_rows: the most that keep the budget (0: not feasible); the least of them serves all."""
    most = F.floor(F.lit(4.0**eps_bits - 1) * (F.col("h2") + F.lit(sigma**2)) + F.lit(1e-9))
    return cover.select("client", F.greatest(most, F.lit(0)).cast("long").alias("coded_rows"))


def privacy_grid(cover: DataFrame, coded: list[int], sigmas: list[float]) -> DataFrame:
    """c, sigma, eps_bits over a grid: the least cover of any client decides."""
    spark = cover.sparkSession
    grid = spark.createDataFrame([(c, float(s)) for c in coded for s in sigmas], "c int, sigma double")
    least = cover.agg(F.min("h2").alias("h2"))
    return grid.crossJoin(F.broadcast(least)).select("c", "sigma", budget_bits(F.col("c"), F.col("h2"), F.col("sigma")).alias("eps_bits"))


def gaussian_information(column, c: int, sigma: float, k: int) -> float:
    """Bits that c coded values of one column tell of its entry k, the others known and the entry standard normal."""
    rest = sum(v * v for i, v in enumerate(column) if i != k) + sigma**2
    return math.inf if rest == 0 else 0.5 * math.log2(1 + c / rest)
