"""Connected components of a link table by alternating large-star and small-star rounds.

Every round is a groupBy-min with partial aggregation and one join, so no task holds the neighbours of
a node; a node with very many links is a skewed join key, which adaptive execution splits.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.llm.common import cut_lineage


def _state(links: DataFrame) -> tuple:
    row = links.agg(F.count("*").alias("n"), F.sum(F.hash("u", "v").cast("long")).alias("s"), F.sum(F.xxhash64("v", "u").cast("decimal(20,0)")).alias("t")).first()
    return tuple(row)


def _large(links: DataFrame) -> DataFrame:
    """Every larger neighbour of u is linked to the least of u and its neighbours."""
    both = cut_lineage(links.select("u", "v").unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v"))))
    least = cut_lineage(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m")))
    moved = both.join(least.hint("merge"), "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.where("u <> v").distinct()


def _small(links: DataFrame) -> DataFrame:
    """u > v in every link: u and its smaller neighbours are linked to the least of them."""
    least = cut_lineage(links.groupBy("u").agg(F.min("v").alias("m")))
    moved = links.join(least.hint("merge"), "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.unionByName(least.select("u", F.col("m").alias("v"))).where("u <> v").distinct()


def components(links: DataFrame, rounds: int = 60) -> DataFrame:
    """``u, v`` (any comparable ids) to ``node, root``: for every linked node the smallest node reachable.

    Nodes without a link are not returned. Null ends, loops and repeated links are ignored.
    """
    e = links.where("u is not null and v is not null and u <> v")
    e = cut_lineage(e.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct())
    before = _state(e)
    if not before[0]:
        return e.select(F.col("u").alias("node"), F.col("v").alias("root"))
    for _ in range(rounds):
        e = cut_lineage(_small(cut_lineage(_large(e))))
        after = _state(e)
        if after == before:
            roots = e.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()
            return e.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(roots)
        before = after
    raise RuntimeError("components did not settle; raise `rounds`")
