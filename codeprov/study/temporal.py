"""Temporal classes of snippet-unit matches: all, disseminator, source."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def classify(matches: DataFrame) -> DataFrame:
    """``snippet_id, posted_at, n_all, n_after, is_disseminator, is_source, first_unit`` of matches with deployed_at.

    Later means strictly after the post. A disseminator has a later unit; a source has one and no unit at or before it.
    """
    later = F.col("deployed_at") > F.col("posted_at")
    g = matches.groupBy("snippet_id", "posted_at").agg(F.count("*").alias("n_all"), F.count_if(later).alias("n_after"), F.min("deployed_at").alias("first_unit"))
    return g.withColumns({"is_disseminator": F.col("n_after") > 0, "is_source": F.coalesce(F.col("first_unit") > F.col("posted_at"), F.lit(False))})


def with_class(matches: DataFrame) -> DataFrame:
    """Each match with its snippet's class and whether its unit is later."""
    kinds = classify(matches).select("snippet_id", "is_disseminator", "is_source")
    return matches.join(kinds, "snippet_id").withColumn("later", F.coalesce(F.col("deployed_at") > F.col("posted_at"), F.lit(False)))


def with_class_of_texts(matches: DataFrame) -> DataFrame:
    """As ``with_class`` for matches with texts, whose units are known by ``first_unit`` and ``last_unit`` (times); later: any unit is."""
    later = lambda at: F.coalesce(F.col(at) > F.col("posted_at"), F.lit(False))
    kinds = matches.groupBy("snippet_id", "posted_at").agg(F.min("first_unit").alias("first_unit"), F.max("last_unit").alias("last_unit"))
    kinds = kinds.select("snippet_id", later("last_unit").alias("is_disseminator"), later("first_unit").alias("is_source"))
    return matches.join(kinds, "snippet_id").withColumn("later", later("last_unit"))
