"""Cost measures: candidate reduction, comparisons, compression, and what a run took."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def reduction(pairs: DataFrame, queries: DataFrame, targets: DataFrame) -> DataFrame:
    """all_pairs, candidates, comparisons (edit distances of part pairs) and candidates / all_pairs of candidate pairs."""
    q = queries.select(F.col("id").alias("query_id"), F.size("subs").alias("qs"))
    t = targets.select(F.col("id").alias("target_id"), F.size("subs").alias("ts"))
    part = pairs.join(q, "query_id").join(t, "target_id").agg(F.count("*").alias("candidates"), F.coalesce(F.sum(F.col("qs").cast("long") * F.col("ts")), F.lit(0)).alias("comparisons"))
    sizes = queries.agg(F.count("*").alias("nq")).join(targets.agg(F.count("*").alias("nt")))
    out = part.join(sizes).withColumn("all_pairs", F.col("nq") * F.col("nt"))
    return out.select("all_pairs", "candidates", "comparisons", F.round(F.col("candidates") / F.col("all_pairs"), 6).alias("ratio"))


def compression(df: DataFrame, prints: DataFrame, id: str, text: str = "text") -> DataFrame:
    """Mean of fingerprint length by text length, over texts that are not empty."""
    both = df.select(F.col(id).alias("id"), F.length(text).alias("n")).where("n > 0").join(prints, "id")
    return both.agg(F.round(F.avg(F.col("len") / F.col("n")), 6).alias("ratio"))


def run(df: DataFrame) -> dict:
    """Seconds, rows, and the shuffled and spilled bytes of the stages that a full evaluation of ``df`` ran."""
    spark = df.sparkSession
    store = spark.sparkContext._jsc.sc().statusStore()
    before = {s.stageId() for s in _stages(store)}
    began = time.time()
    rows = df.count()
    took = time.time() - began
    new = [s for s in _stages(store) if s.stageId() not in before]
    total = lambda name: sum(int(getattr(s, name)()) for s in new)
    return {"seconds": took, "rows": rows, "shuffle_bytes": total("shuffleWriteBytes"), "spill_bytes": total("diskBytesSpilled"), "peak_memory": max([int(s.peakExecutionMemory()) for s in new] or [0])}


def _stages(store) -> list:
    found = store.stageList(None)
    return [found.apply(i) for i in range(found.size())]
