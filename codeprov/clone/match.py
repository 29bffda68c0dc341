"""Clone search: fingerprints, candidates, order-free score, threshold."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from codeprov.clone.candidates import retrieve
from codeprov.clone.normalise import strip_layout
from codeprov.clone.score import order_free
from codeprov.session import cut_lineage


@dataclass(frozen=True)
class Setting:
    """N-gram length, least share of the query's grams, least score (0 to 1)."""

    n: int = 3
    eta: float = 0.5
    eps: float = 0.7


DEFAULT = Setting()
CONSERVATIVE = Setting(3, 0.5, 0.9)


def scored(queries: DataFrame, targets: DataFrame, n: int = 3, eta: float = 0.5, strategy: str = "auto", direction: str = "forward", self_join: bool = False) -> DataFrame:
    """Candidates with their score; both sides are fingerprint tables ``id, subs``."""
    pairs = retrieve(queries, targets, n, eta, strategy, self_join=self_join)
    q = queries.select(F.col("id").alias("query_id"), F.col("subs").alias("q"))
    t = targets.select(F.col("id").alias("target_id"), F.col("subs").alias("t"))
    out = pairs.join(q, "query_id").join(t, "target_id")
    return out.select("query_id", "target_id", "shared", "n_grams", "containment", order_free("q", "t", direction).alias("score"))


def find_clones(queries: DataFrame, targets: DataFrame, setting: Setting = DEFAULT, strategy: str = "auto", direction: str = "forward") -> DataFrame:
    """Pairs whose score reaches the setting's threshold."""
    return scored(queries, targets, setting.n, setting.eta, strategy, direction).where(F.col("score") >= 100 * setting.eps)


def self_clones(prints: DataFrame, setting: Setting = DEFAULT, strategy: str = "auto") -> DataFrame:
    """All against all within one table, a row never against itself."""
    return scored(prints, prints, setting.n, setting.eta, strategy, self_join=True).where(F.col("score") >= 100 * setting.eps)


def collapse(prints: DataFrame, *weights: str) -> tuple[DataFrame, DataFrame]:
    """Equal fingerprints as one: ``id, subs`` of the least id of each class, and ``id, rep`` (and ``weights``) of all rows."""
    keyed = cut_lineage(prints.select("id", "subs", F.sha2(F.array_join("subs", "."), 256).alias("_k"), *weights))
    reps = keyed.groupBy("_k").agg(F.min(F.struct("id", "subs")).alias("r")).select("_k", "r.id", "r.subs")
    members = keyed.select("id", "_k", *weights).join(reps.select("_k", F.col("id").alias("rep")), "_k").drop("_k")
    return cut_lineage(reps.drop("_k")), members


def class_clones(reps: DataFrame, setting: Setting = DEFAULT) -> DataFrame:
    """``query_id, target_id`` of ``self_clones`` between classes, and of each class that has a part with itself."""
    own = reps.where(F.size("subs") > 0).select(F.col("id").alias("query_id"), F.col("id").alias("target_id"))
    return self_clones(reps, setting).select("query_id", "target_id").unionByName(own)


def clone_type(q: Column, t: Column, canonical_q: Column, canonical_t: Column, score: Column, eps: float = 0.7, profile: str = "prose") -> Column:
    """I: equal but for layout; II: equal but for names; III: score over the threshold; null otherwise."""
    return F.when(strip_layout(q, profile) == strip_layout(t, profile), "I").when(canonical_q == canonical_t, "II").when(score >= 100 * eps, "III")
