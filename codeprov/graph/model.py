"""Storing property graphs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

BUCKETS = 64


def save(nodes: DataFrame, edges: DataFrame, path: str, buckets: int = BUCKETS) -> None:
    """Both tables cut by a hash of the unit, so that a unit's rows lie together and parts can be read alone."""
    for name, df in (("nodes", nodes), ("edges", edges)):
        part = df.withColumn("bucket", F.pmod(F.xxhash64("unit_id"), F.lit(buckets)).cast("int"))
        part.repartition("bucket").sortWithinPartitions("unit_id").write.mode("overwrite").partitionBy("bucket").parquet(f"{path}/{name}")


def load(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame]:
    return tuple(spark.read.parquet(f"{path}/{n}").drop("bucket") for n in ("nodes", "edges"))
