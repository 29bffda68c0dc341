"""Streams over the given tables: a file source with its schema, and a run over all that is there."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from codeprov.session import shared_folder

WATERMARK = "1 hour"


def events(spark: SparkSession, sf_dir: str, watermark: str = WATERMARK) -> DataFrame:
    """``events`` as a stream with event time ``ts`` (as an instant, which watermarks ask for)."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    raw = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark)


def place(spark: SparkSession, name: str) -> str:
    """A fresh folder that driver and executors share."""
    return f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"


def run(stream: DataFrame, mode: str, each: Callable[[DataFrame, int], None] | None = None) -> DataFrame:
    """Everything that is there (availableNow), then the result as a batch.

    Complete mode keeps the newest snapshot, append mode adds every batch; both are files in the shared
    folder, so a restarted batch writes its own part again and nothing twice.
    """
    spark = stream.sparkSession
    where = place(spark, "stream")
    schema = stream.schema

    def write(batch: DataFrame, number: int) -> None:
        to = f"{where}/data/complete" if mode == "complete" else f"{where}/data/batch={number}"
        batch.write.mode("overwrite").parquet(to)
        if each is not None:
            each(batch, number)

    q = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{where}/state").trigger(availableNow=True).foreachBatch(write).start()
    q.awaitTermination()
    data = spark.read.schema(schema).option("recursiveFileLookup", "true").parquet(f"{where}/data")
    return data.select(*(F.col(n) for n in schema.names))


def arrive(parts: Iterable[DataFrame], build: Callable[[DataFrame], DataFrame], mode: str, write: Callable[[DataFrame, str], None] | None = None, watermark: str | None = WATERMARK) -> DataFrame:
    """The log of a stream whose input arrives in ``parts``, a restart of the query after each: rows and their ``batch``.

    ``build`` makes the query of the stream, ``write`` (of a micro-batch and its folder) replaces the plain write. A
    micro-batch that runs again writes its own folder again, so nothing is there twice.
    """
    where, schema = None, None
    for part in parts:
        spark = part.sparkSession
        where = where or place(spark, "arrivals")
        part.write.mode("append").parquet(f"{where}/in")
        schema = schema or spark.read.parquet(f"{where}/in").schema
        raw = spark.readStream.schema(schema).parquet(f"{where}/in")
        stream = build(raw.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark) if watermark else raw)

        def put(batch: DataFrame, number: int) -> None:
            to = f"{where}/out/batch={number}"
            if write is not None:
                write(batch, to)
            else:
                batch.write.mode("overwrite").parquet(to)

        q = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{where}/state").trigger(availableNow=True).foreachBatch(put).start()
        q.awaitTermination()
    return spark.read.parquet(f"{where}/out")


def newest(log: DataFrame, keys: list[str]) -> DataFrame:
    """The upsert of a log: of each key the row of its last micro-batch."""
    rest = [c for c in log.columns if c not in (*keys, "batch")]
    last = log.groupBy(*keys).agg(F.max_by(F.struct(*rest), "batch").alias("_last"))
    return last.select(*keys, *(F.col(f"_last.{c}").alias(c) for c in rest))
