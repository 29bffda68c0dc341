"""Views of a snippet's post against the distinct units that took it over."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.study import temporal


def table(matches: DataFrame, views: DataFrame) -> DataFrame:
    """``class, snippet_id, views, adopters`` (over 0) for the three classes; matches need code_hash."""
    m = temporal.with_class(matches)
    parts = [("all", F.lit(True)), ("disseminator", F.col("is_disseminator") & F.col("later")), ("source", F.col("is_source"))]
    rows = [m.where(w).groupBy("snippet_id").agg(F.count_distinct("code_hash").alias("adopters")).withColumn("class", F.lit(k)) for k, w in parts]
    out = reduce(DataFrame.unionByName, rows).join(views, "snippet_id", "left")
    return out.select("class", "snippet_id", F.coalesce("views", F.lit(0)).alias("views"), "adopters")


def top(posts: DataFrame, k: int, views: str = "views") -> DataFrame:
    """The most viewed posts, who should publish vetted code first."""
    return posts.orderBy(F.desc(views), *[c for c in posts.columns if c != views]).limit(k)
