"""Candidate retrieval: targets that share at least a part eta of a query's N-grams.

Two strategies with equal answers; ``auto`` takes ``plain`` for queries that can be broadcast and ``prefix``
for the others. ``plain`` joins all postings. ``prefix`` probes only the rarest grams
of each query: with G grams of which ceil(eta G) must be shared, any G - ceil(eta G) + 1 of them hit every
answer, so the postings of frequent grams are never joined; the exact count is then taken on survivors.
``minhash`` is an opt-in approximation (recall is reported against the exact ones).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from codeprov.clone.ngram import grams
from codeprov.session import cut_lineage

#: Query postings (rows) up to which the query side is broadcast; beyond it both sides are shuffled by gram.
MOST_BROADCAST = 200_000


def gram_table(prints: DataFrame, n: int = 3) -> DataFrame:
    """``id, grams, n_grams`` of fingerprints that have a part.

    One whose parts are all shorter than ``n`` has one gram, the whole string (it meets only its equals: it is
    shorter than ``n`` or holds a separator, which no other gram does).
    """
    found = grams("subs", n)
    whole = F.when(F.size("subs") > 0, F.array(F.array_join("subs", "."))).otherwise(found)
    return prints.select("id", F.when(F.size(found) > 0, found).otherwise(whole).alias("grams")).withColumn("n_grams", F.size("grams")).where("n_grams > 0")


def index(table: DataFrame) -> DataFrame:
    """Postings ``gram, id, size`` (grams of the fingerprint)."""
    return table.select(F.explode("grams").alias("gram"), "id", F.col("n_grams").alias("size"))


def stats(table: DataFrame) -> DataFrame:
    """``gram, df``; at most 64^n rows of n letters, whatever the corpus."""
    return index(table).groupBy("gram").agg(F.count("*").alias("df"))


def needed(eta: float, rounding: str = "exact") -> str:
    """SQL of the number of shared grams asked for."""
    if rounding == "exact":
        return f"{eta} * n_grams"
    return f"{'ceil' if rounding == 'up' else 'floor'}({eta} * n_grams)"


def retrieve(queries: DataFrame, targets: DataFrame, n: int = 3, eta: float = 0.5, strategy: str = "auto", rounding: str = "exact", self_join: bool = False, most_broadcast: int = MOST_BROADCAST, bands: int = 16, rows: int = 2) -> DataFrame:
    """``query_id, target_id, shared, n_grams, containment`` from two fingerprint tables (``id, subs``).

    ``self_join`` leaves out pairs of one id. The query side is broadcast only after its size was counted.
    """
    q, t = gram_table(queries, n), gram_table(targets, n)
    if strategy == "minhash":
        return _minhash(q, t, eta, bands, rows, self_join)
    small = (q.agg(F.sum("n_grams")).first()[0] or 0) <= most_broadcast
    if strategy == "auto":
        strategy = "plain" if small and not self_join else "prefix"
    if strategy == "prefix":
        probes = _prefix(q, t, eta, rounding)
    elif strategy == "plain":
        probes = q.select(F.explode("grams").alias("gram"), F.col("id").alias("query_id"), "n_grams")
    else:
        raise ValueError("strategy must be auto, plain, prefix or minhash")
    probes = F.broadcast(probes) if small else probes
    # A target with fewer grams than must be shared cannot answer; the join itself leaves it out.
    postings = index(t).withColumnsRenamed({"id": "target_id", "gram": "posted"})
    joined = postings.join(probes, (F.col("posted") == F.col("gram")) & F.expr(f"size >= {needed(eta, rounding)}"))
    if self_join:
        joined = joined.where("query_id <> target_id")
    if strategy == "plain":
        counted = joined.groupBy("query_id", "target_id").agg(F.count("*").alias("shared"), F.first("n_grams").alias("n_grams"))
    else:
        pairs = joined.select("query_id", "target_id").distinct()
        left = q.select(F.col("id").alias("query_id"), F.col("grams").alias("qg"), "n_grams")
        right = t.select(F.col("id").alias("target_id"), F.col("grams").alias("tg"))
        counted = pairs.join(left, "query_id").join(right, "target_id").select("query_id", "target_id", F.size(F.array_intersect("qg", "tg")).cast("long").alias("shared"), "n_grams")
    return counted.where(f"shared >= {needed(eta, rounding)}").withColumn("containment", F.col("shared") / F.col("n_grams"))


def _prefix(q: DataFrame, t: DataFrame, eta: float, rounding: str = "exact") -> DataFrame:
    """The rarest grams of each query that must hit any answer."""
    asked = q.select("id", "n_grams", F.explode("grams").alias("gram"))
    ranked = asked.join(stats(t), "gram")
    by = Window.partitionBy("id").orderBy("df", "gram")
    # Grams that no target has are the rarest of all: they use up places of the prefix without a posting.
    found = F.count("*").over(Window.partitionBy("id"))
    ranked = ranked.withColumns({"place": F.row_number().over(by), "missing": F.col("n_grams") - found})
    return ranked.where(f"missing + place <= n_grams - ceil({needed(eta, rounding)}) + 1").select("gram", F.col("id").alias("query_id"), "n_grams")


def _seeder(seed: int):
    return lambda gram: F.xxhash64(gram, F.lit(seed))


def _minhash(q: DataFrame, t: DataFrame, eta: float, bands: int, rows: int, self_join: bool) -> DataFrame:
    def banded(table: DataFrame, name: str) -> DataFrame:
        least = lambda b: F.hash(*(F.array_min(F.transform("grams", _seeder(b * rows + r))) for r in range(rows)))
        return table.select(F.col("id").alias(name), F.col("grams").alias(f"{name}_g"), "n_grams", F.posexplode(F.array(*(least(b) for b in range(bands)))).alias("band", "h"))

    a, b = banded(q, "query_id"), banded(t, "target_id").drop("n_grams")
    pairs = a.join(b, ["band", "h"]).where("query_id <> target_id" if self_join else "true").dropDuplicates(["query_id", "target_id"])
    shared = F.size(F.array_intersect("query_id_g", "target_id_g")).cast("long")
    return pairs.select("query_id", "target_id", shared.alias("shared"), "n_grams").where(f"shared >= {eta} * n_grams").withColumn("containment", F.col("shared") / F.col("n_grams"))


def materialised(pairs: DataFrame) -> DataFrame:
    """Pairs written once: they are reused by every threshold of a sweep."""
    return cut_lineage(pairs)
