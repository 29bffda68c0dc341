"""Reading tables and code trees, and writing results. Everything goes through Spark's own readers and writers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType


def load(spark: SparkSession, path: str, kind: str = "parquet", schema: StructType | str | None = None, **options) -> DataFrame:
    """parquet, json, csv or orc; a schema saves the pass that would infer one."""
    reader = spark.read.options(**options)
    return (reader.schema(schema) if schema is not None else reader).format(kind).load(path)


def code_tree(spark: SparkSession, path: str, pattern: str = "*.sol") -> DataFrame:
    """``path, code, bytes``: every file of a tree as one row; unreadable bytes become the replacement sign."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", pattern).option("recursiveFileLookup", "true").load(path)
    return files.select("path", F.decode(F.col("content"), "UTF-8").alias("code"), F.col("length").alias("bytes"))


def whole_texts(spark: SparkSession, path: str) -> DataFrame:
    """``code, path``: text files as they are, one row each."""
    return spark.read.text(path, wholetext=True).select(F.col("value").alias("code"), F.input_file_name().alias("path"))


def save(df: DataFrame, path: str, kind: str = "parquet", by: list[str] = (), sort: list[str] = (), **options) -> None:
    """Partitioned by ``by`` (rows of one value go to one task first, so that no task writes to every folder)."""
    out = df.repartition(*by) if by else df
    out = out.sortWithinPartitions(*sort) if sort else out
    writer = out.write.mode("overwrite").options(**options).format(kind)
    (writer.partitionBy(*by) if by else writer).save(path)


def save_bucketed(df: DataFrame, name: str, key: str, buckets: int, sort: str | None = None) -> None:
    """A table bucketed by a join key: two of them join without a shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(sort or key).saveAsTable(name)
