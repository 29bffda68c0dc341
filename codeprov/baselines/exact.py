"""Ordinary hashes: one change alters all."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def hash_match(queries: DataFrame, targets: DataFrame, query_id: str, target_id: str, text: str = "text") -> DataFrame:
    """Pairs whose whole texts are equal."""
    q = queries.select(F.col(query_id).alias("query_id"), F.sha2(text, 256).alias("h"))
    t = targets.select(F.col(target_id).alias("target_id"), F.sha2(text, 256).alias("h"))
    return q.join(t, "h").select("query_id", "target_id")


def groups(df: DataFrame, key) -> DataFrame:
    """groups, rows and surplus (rows beyond the first of their group) of rows by a key."""
    g = df.select(F.sha2(key, 256).alias("h")).groupBy("h").agg(F.count("*").alias("n"))
    return g.agg(F.count("*").alias("groups"), F.coalesce(F.sum("n"), F.lit(0)).alias("rows"), F.coalesce(F.sum(F.col("n") - 1), F.lit(0)).alias("surplus"))
