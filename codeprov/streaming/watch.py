"""Alerts: a post that is similar to a known weak snippet, flagged when it arrives."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.clone import fingerprint, match


def alerts(stream: DataFrame, index: DataFrame, key: str = "event_id") -> DataFrame:
    """Posts of the stream whose unit is in the static index (``unit_id``), per day of arrival.

    The index is planned anew for each micro-batch, so that a rewritten table is picked up.
    """
    hit = stream.join(index.select(F.col("unit_id").alias(key)).distinct(), key)
    return hit.groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("alerts")).select(F.col("w.start").alias("window_start"), "alerts")


def similar(known: DataFrame, id: str, setting: match.Setting = match.DEFAULT):
    """A writer of micro-batches for ``replay.arrive``: arriving posts (``id``, text) similar to a known fingerprint.

    Each micro-batch is fingerprinted, met with the grams of ``known`` (``id, subs``) and scored; only its own
    posts are looked at, so the work grows with what arrives.
    """

    def write(batch: DataFrame, to: str) -> None:
        found = match.find_clones(known, fingerprint.build(batch, id), setting)
        found.select("query_id", "target_id", "score").write.mode("overwrite").parquet(to)

    return write
