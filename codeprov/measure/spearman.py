"""Rank correlation with average ranks, at any size."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from codeprov.functions.pvalue import p_value

__all__ = ["average_ranks", "p_value", "pearson", "spearman"]


def average_ranks(df: DataFrame, column: str, by: list[str], out: str) -> DataFrame:
    """``df`` with the average rank of ``column`` within ``by``.

    Distinct values with their counts are ranked (a running sum), not the rows, and the rows get their value's
    rank by a join: the window sees one row for each distinct value and never the whole input in one task
    unless all values differ; then it is split by ranges first.
    """
    counts = df.groupBy(*by, column).agg(F.count("*").alias("_n"))
    coarse = counts.withColumn("_c", _range_of(counts, column))
    per = coarse.groupBy(*by, "_c").agg(F.sum("_n").alias("_m"))
    before = per.withColumn("_o", F.coalesce(F.sum("_m").over(Window.partitionBy(*by).orderBy("_c").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))) if by else per.withColumn("_o", F.coalesce(F.sum("_m").over(Window.partitionBy(F.lit(0)).orderBy("_c").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    inside = Window.partitionBy(*by, "_c").orderBy(column).rowsBetween(Window.unboundedPreceding, -1)
    ranked = coarse.withColumn("_i", F.coalesce(F.sum("_n").over(inside), F.lit(0))).join(F.broadcast(before.drop("_m")) if not by else before.drop("_m"), [*by, "_c"])
    ranked = ranked.select(*by, column, (F.col("_o") + F.col("_i") + (F.col("_n") + 1) / 2).alias(out))
    return df.join(ranked, [*by, column])


def _range_of(counts: DataFrame, column: str):
    """A monotone coarse value: which of up to 256 quantile ranges of the distinct values a value falls in."""
    cuts = counts.agg(F.percentile_approx(F.col(column).cast("double"), [i / 256 for i in range(1, 256)], 10000)).first()[0] or []
    cuts = sorted(set(cuts))
    return F.size(F.filter(F.array(*(F.lit(float(c)) for c in cuts)), lambda c: c <= F.col(column))) if cuts else F.lit(0)


def correlation(x: str, y: str):
    """Pearson's coefficient as an aggregate; NaN where a column is constant or there is one pair."""
    return F.coalesce(F.try_divide(F.covar_pop(x, y), F.stddev_pop(x) * F.stddev_pop(y)), F.lit(float("nan")))


def spearman(df: DataFrame, x: str, y: str, by: list[str]) -> DataFrame:
    """``by, n, rho``; pairs with a null are left out, rho is NaN where a column is constant."""
    clean = df.where(F.col(x).isNotNull() & F.col(y).isNotNull()).select(*by, x, y)
    ranked = average_ranks(average_ranks(clean, x, by, "_rx"), y, by, "_ry")
    return ranked.groupBy(*by).agg(F.count("*").alias("n"), correlation("_rx", "_ry").alias("rho"))


def pearson(df: DataFrame, x: str, y: str, by: list[str]) -> DataFrame:
    """``by, n, r``; r is NaN where a column is constant."""
    return df.groupBy(*by).agg(F.count("*").alias("n"), correlation(x, y).alias("r"))
