"""Samples for manual review and their tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def sample(findings: DataFrame, k: int, seed: int = 7) -> DataFrame:
    """About ``k`` findings, as many of each category as there can be, snippets and units used once each.

    The order inside a category is a seeded hash of the pair, then the rule, so that a sample can be drawn again.
    """
    h = F.xxhash64("snippet_id", "unit_id", F.lit(seed))
    one = findings.withColumn("_h", h)
    for c in ("snippet_id", "unit_id"):
        one = one.withColumn("_r", F.row_number().over(Window.partitionBy(c).orderBy("_h", "rule_id"))).where("_r = 1").drop("_r")
    ranked = one.withColumn("_r", F.row_number().over(Window.partitionBy("category").orderBy("_h", "rule_id")))
    return ranked.orderBy("_r", "category").limit(k).drop("_h", "_r")


def contingency(reviewed: DataFrame) -> DataFrame:
    """``clone_ok, snippet_ok, unit_ok, n`` for all eight cells."""
    spark = reviewed.sparkSession
    cells = spark.createDataFrame([(a, b, c) for a in (True, False) for b in (True, False) for c in (True, False)], "clone_ok boolean, snippet_ok boolean, unit_ok boolean")
    n = reviewed.groupBy("clone_ok", "snippet_ok", "unit_ok").agg(F.count("*").alias("n"))
    return cells.join(n, ["clone_ok", "snippet_ok", "unit_ok"], "left").na.fill(0)


def causes(reviewed: DataFrame) -> DataFrame:
    """False positives by category and cause."""
    return reviewed.groupBy("category", "cause").agg(F.count("*").alias("n"))


def not_vetted(units: DataFrame, vetted: DataFrame, eps: float = 0.9) -> DataFrame:
    """Fingerprints (``id, subs``) of units that no vetted fingerprint is similar to; equal ones are compared once."""
    from codeprov.clone import match

    reps, members = match.collapse(units)
    found = match.find_clones(match.collapse(vetted)[0], reps, match.Setting(3, 0.5, eps)).select(F.col("target_id").alias("rep")).distinct()
    return units.join(members.join(found, "rep", "left_semi").select("id"), "id", "left_anti")
