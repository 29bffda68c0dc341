"""Reachability over one kind of edge of a graph table (``unit_id, src, dst, kind``).

A path that must avoid or pass a node is never enumerated: walks on the graph without the node, and two
reachabilities through it, answer the same question in polynomial time.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.session import cut_lineage

#: Lineage is cut after so many hops.
CUT_EVERY = 4


def reach(edges: DataFrame, kind: str, sources: DataFrame, max_hops: int | None = None, avoid: DataFrame | None = None, reverse: bool = False) -> DataFrame:
    """``unit_id, src, dst, hops`` (least) from each source (``unit_id, node_id``) over ``kind``; hop 0 is left out.

    Semi-naive: every round joins only the newest pairs, and what was seen is taken out by an anti-join.
    ``avoid`` (``unit_id, node_id``) may not be entered. All joins share ``unit_id``, so no edge leaves a unit.
    """
    a, b = ("dst", "src") if reverse else ("src", "dst")
    step = edges.where(F.col("kind") == kind).select("unit_id", F.col(a).alias("at"), F.col(b).alias("to"))
    if avoid is not None:
        step = step.join(avoid.select("unit_id", F.col("node_id").alias("to")), ["unit_id", "to"], "left_anti")
    step = cut_lineage(step.distinct())
    front = sources.select("unit_id", F.col("node_id").alias("src"), F.col("node_id").alias("dst")).distinct()
    seen, hops = None, 0
    while max_hops is None or hops < max_hops:
        hops += 1
        new = front.withColumnRenamed("dst", "at").join(step, ["unit_id", "at"]).select("unit_id", "src", F.col("to").alias("dst")).distinct()
        if seen is not None:
            new = new.join(seen, ["unit_id", "src", "dst"], "left_anti")
        new = cut_lineage(new.withColumn("hops", F.lit(hops)))
        if new.isEmpty():
            break
        seen = new if seen is None else seen.unionByName(new)
        if hops % CUT_EVERY == 0:
            seen = cut_lineage(seen)
        front = new.drop("hops")
    return seen if seen is not None else front.where("false").withColumn("hops", F.lit(0))


def formed(edges: DataFrame, kind: str, sources: DataFrame, budget: int) -> DataFrame:
    """``unit_id, hops, pairs``: pairs that a search from ``sources`` has formed after each hop.

    A unit whose pairs exceed ``budget`` is searched no further, so the work is bounded by the budget and by the
    widest step of a unit beyond it.
    """
    step = cut_lineage(edges.where(F.col("kind") == kind).select("unit_id", F.col("src").alias("at"), F.col("dst").alias("to")).distinct())
    front = sources.select("unit_id", F.col("node_id").alias("src"), F.col("node_id").alias("dst")).distinct()
    seen, counts, hops = None, None, 0
    while True:
        hops += 1
        new = front.withColumnRenamed("dst", "at").join(step, ["unit_id", "at"]).select("unit_id", "src", F.col("to").alias("dst")).distinct()
        if seen is not None:
            new = new.join(seen, ["unit_id", "src", "dst"], "left_anti")
        new = cut_lineage(new)
        if new.isEmpty():
            break
        seen = cut_lineage(new if seen is None else seen.unionByName(new))
        now = cut_lineage(seen.groupBy("unit_id").agg(F.count("*").alias("pairs")))
        counts = now.withColumn("hops", F.lit(hops)) if counts is None else counts.unionByName(now.withColumn("hops", F.lit(hops)))
        within = now.where(F.col("pairs") <= budget)
        front = new.join(within, "unit_id", "left_semi")
        seen = seen.join(within, "unit_id", "left_semi")
    return (counts if counts is not None else front.where("false").select("unit_id", F.lit(0).cast("long").alias("pairs"), F.lit(0).alias("hops"))).select("unit_id", "hops", "pairs")


def trails(edges: DataFrame, kind: str, src: int, dst: int, max_hops: int) -> DataFrame:
    """All edge-simple paths, for tiny graphs: the exponential reference of ``reach``. ``path`` lists the nodes."""
    step = edges.where(F.col("kind") == kind).select("unit_id", F.col("src").alias("at"), F.col("dst").alias("to"))
    front = step.where(F.col("at") == src).select("unit_id", F.array("at", "to").alias("path"), F.array(F.struct("at", "to")).alias("used"))
    out = front
    for _ in range(max_hops - 1):
        front = front.withColumn("at", F.element_at("path", -1)).join(step, ["unit_id", "at"]).where(~F.array_contains("used", F.struct("at", "to"))).select("unit_id", F.array_append("path", F.col("to")).alias("path"), F.array_append("used", F.struct("at", "to")).alias("used"))
        out = out.unionByName(front)
    return out.where(F.element_at("path", -1) == dst).select("unit_id", "path")
