"""Descriptive statistics of snippets and units."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def loc(df: DataFrame, text: str = "text") -> DataFrame:
    """``metric, value``: min, mean, median and max of lines per text."""
    lines = df.where(F.col(text).isNotNull()).select(F.size(F.split(text, "\n")).alias("n"))
    row = lines.agg(F.min("n").cast("double").alias("min"), F.round(F.avg("n"), 6).alias("mean"), F.percentile("n", 0.5).alias("median"), F.max("n").cast("double").alias("max"))
    return row.unpivot([], ["min", "mean", "median", "max"], "metric", "value")


def shares(df: DataFrame, key: str, total: str = "n") -> DataFrame:
    """``key, n, share`` of rows by a key; the total comes from the groups, not from a second scan."""
    g = df.groupBy(key).agg(F.count("*").alias("n"))
    return g.join(F.broadcast(g.agg(F.sum("n").alias("_all")))).select(key, "n", F.round(F.col("n") / F.col("_all"), 6).alias("share"))


def versions(df: DataFrame, version: str, at: str, recent_from) -> DataFrame:
    """``version, n, share, recent_n, recent_share``: over all rows, and over those from a time on."""
    g = df.groupBy(F.col(version).alias("version")).agg(F.count("*").alias("n"), F.count_if(F.col(at) >= recent_from).alias("recent_n"))
    all_ = g.agg(F.sum("n").alias("_a"), F.sum("recent_n").alias("_r"))
    return g.join(F.broadcast(all_)).select("version", "n", F.round(F.col("n") / F.col("_a"), 6).alias("share"), "recent_n", F.round(F.try_divide("recent_n", "_r"), 6).alias("recent_share"))


def parse_gain(df: DataFrame, lenient: str = "lenient_ok", strict: str = "strict_ok") -> DataFrame:
    """Texts that only the lenient grammar takes."""
    return df.agg(F.count_if(F.col(lenient) & ~F.col(strict)).alias("gain"))
