"""Counts along the way from posts to validated units."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: The ten categories of the taxonomy (fixed names).
CATEGORIES = ("access control", "arithmetic", "bad randomness", "denial of service", "front running", "reentrancy", "short addresses", "time manipulation", "unchecked low level calls", "unknown unknowns")


def collection(stages: DataFrame) -> DataFrame:
    """``site, posts, snippets, in_language, parseable, uniq`` and a total; one row of ``stages`` is a snippet
    (or a post without one) with site, post_id, snippet (bool), in_language, parseable, first (bool)."""
    good = F.col("in_language") & F.col("parseable")
    per = stages.groupBy("site").agg(F.count_distinct("post_id").alias("posts"), F.count_if("snippet").alias("snippets"), F.count_if("in_language").alias("in_language"), F.count_if(good).alias("parseable"), F.count_if(good & F.col("first")).alias("uniq"))
    sums = [F.sum(c).alias(c) for c in ("posts", "snippets", "in_language", "parseable", "uniq")]
    return per.unionByName(per.agg(*sums).withColumn("site", F.lit("total")))


def units_by_class(classified: DataFrame) -> DataFrame:
    """Units matched by any snippet, by a disseminator, by a source."""
    return classified.agg(F.count_distinct("unit_id").alias("any"), F.count_distinct(F.when(F.col("is_disseminator") & F.col("later"), F.col("unit_id"))).alias("disseminator"), F.count_distinct(F.when(F.col("is_source"), F.col("unit_id"))).alias("source"))


def candidates(df: DataFrame) -> DataFrame:
    """Candidates before and after duplicate code is taken once."""
    return df.agg(F.count("*").alias("units"), F.count_distinct("code_hash").alias("codes"))


def categories(findings: DataFrame) -> DataFrame:
    """``category, snippets, units`` for all ten categories, also those without a finding."""
    spark = findings.sparkSession
    all_ = spark.createDataFrame([(c,) for c in CATEGORIES], "category string")
    found = findings.groupBy("category").agg(F.count_distinct("snippet_id").alias("snippets"), F.count_distinct("unit_id").alias("units"))
    return all_.join(found, "category", "left").na.fill(0)


def phases(status: DataFrame) -> DataFrame:
    return status.groupBy("phase", "status").agg(F.count("*").alias("n"))


def validated_share(snippets: DataFrame) -> DataFrame:
    """Of candidate snippets (``snippet_id, validated``) the share with a validated unit."""
    per = snippets.groupBy("snippet_id").agg(F.bool_or("validated").alias("v"))
    return per.agg(F.count("*").alias("candidates"), F.count_if("v").alias("validated"), F.round(F.try_divide(F.count_if("v").cast("double"), F.count("*")), 6).alias("share"))
