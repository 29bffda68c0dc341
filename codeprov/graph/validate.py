"""Two-phase validation: a full search under a budget, then ever shorter positive paths for what was left."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.graph import closure
from codeprov.graph.pattern import Rule, evaluate
from codeprov.session import cut_lineage


def two_phase(nodes: DataFrame, edges: DataFrame, rules: list[Rule], kind: str, sources: DataFrame, budget: int, hop_schedule: tuple[int, ...] = (16, 8, 4, 2)) -> tuple[DataFrame, DataFrame]:
    """Findings (with ``phase``), and ``unit_id, phase, status`` with status ok or budget_exceeded.

    A unit's cost is what a search from ``sources`` (``unit_id, node_id``) over ``kind`` is seen to form: pairs of
    nodes, not seconds, so that a run decides alike on any machine. Phase 0 searches whole units whose cost is
    within the budget. The others are searched with each limit of the schedule in turn, once the pairs up to
    that limit fit; mitigations are never cut. An empty schedule leaves them unresolved.
    """
    units = nodes.select("unit_id").distinct()
    formed = closure.formed(edges, kind, sources, budget)
    pending = cut_lineage(units)
    findings, status = None, None
    for phase, hops in enumerate((None, *hop_schedule)):
        cost = (formed if hops is None else formed.where(F.col("hops") <= hops)).groupBy("unit_id").agg(F.max("pairs").alias("cost"))
        fits = cut_lineage(pending.join(cost, "unit_id", "left").where(F.coalesce("cost", F.lit(0)) <= budget).select("unit_id"))
        if fits.isEmpty():
            continue
        n, e = (d.join(fits, "unit_id", "left_semi") for d in (nodes, edges))
        found = cut_lineage(evaluate(n, e, rules, hops).withColumn("phase", F.lit(phase)))
        done = fits.select("unit_id", F.lit(phase).alias("phase"), F.lit("ok").alias("status"))
        findings = found if findings is None else findings.unionByName(found, allowMissingColumns=True)
        status = done if status is None else status.unionByName(done)
        pending = cut_lineage(pending.join(fits, "unit_id", "left_anti"))
        if pending.isEmpty():
            break
    rest = pending.select("unit_id", F.lit(None).cast("int").alias("phase"), F.lit("budget_exceeded").alias("status"))
    if status is None:
        return evaluate(nodes, edges, rules).where("false").withColumn("phase", F.lit(0)), rest
    return findings, status.unionByName(rest)
