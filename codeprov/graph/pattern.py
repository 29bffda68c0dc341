"""Three-part rules over graph tables: a base pattern, any of some conditions of relevancy, none of the mitigations.

The parts are DataFrames of bindings; the compiler joins them as left semi (any relevancy) and left anti
(every mitigation). A hop limit may cut positive parts only: a mitigation is always searched in full.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.graph import closure

#: Builds bindings from (nodes, edges, hop limit); a mitigation gets None as its limit.
Part = Callable[[DataFrame, DataFrame, int | None], DataFrame]


@dataclass(frozen=True)
class Rule:
    rule_id: str
    category: str
    base: Part
    keys: tuple[str, ...]
    relevancy: tuple[Part, ...] = ()
    mitigations: tuple[Part, ...] = field(default=())


def evaluate(nodes: DataFrame, edges: DataFrame, rules: list[Rule], max_hops: int | None = None, use_relevancy: bool = True, use_mitigations: bool = True) -> DataFrame:
    """``unit_id, rule_id, category`` and each rule's binding as a struct of its keys, for the given rules only."""
    out = []
    for r in rules:
        found = r.base(nodes, edges, max_hops)
        keys = ["unit_id", *r.keys]
        if use_relevancy and r.relevancy:
            wanted = reduce(DataFrame.unionByName, [p(nodes, edges, max_hops).select(*keys) for p in r.relevancy])
            found = found.join(wanted, keys, "left_semi")
        if use_mitigations:
            for p in r.mitigations:
                found = found.join(p(nodes, edges, None).select(*keys), keys, "left_anti")
        out.append(found.select("unit_id", F.lit(r.rule_id).alias("rule_id"), F.lit(r.category).alias("category"), *r.keys))
    return reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), out)


def on_path(edges: DataFrame, kind: str, pairs: DataFrame, marked: DataFrame, max_hops: int | None = None) -> DataFrame:
    """Of ``pairs`` (``unit_id, src, dst``) those with a node of ``marked`` (``unit_id, node_id``) on a walk between them.

    The two ends count as on the walk only where another walk passes them. Walks are never listed: the node is
    reached from ``src``, and ``dst`` from the node. ``max_hops`` bounds each of the two parts.
    """
    ends = pairs.select("unit_id", "src", "dst").distinct()
    mids = marked.select("unit_id", "node_id").distinct()
    to = closure.reach(edges, kind, ends.select("unit_id", F.col("src").alias("node_id")), max_hops).select("unit_id", "src", F.col("dst").alias("node_id")).join(mids, ["unit_id", "node_id"], "left_semi")
    on = closure.reach(edges, kind, to.select("unit_id", "node_id"), max_hops).select("unit_id", F.col("src").alias("node_id"), "dst")
    through = to.join(on.join(ends.select("unit_id", "dst").distinct(), ["unit_id", "dst"], "left_semi"), ["unit_id", "node_id"])
    return ends.join(through, ["unit_id", "src", "dst"], "left_semi")


def exits(nodes: DataFrame, edges: DataFrame, kind: str = "EOG", persisting: bool = True) -> DataFrame:
    """``unit_id, node_id`` of nodes that no edge of ``kind`` leaves; ``persisting`` leaves out those labelled Rollback."""
    left = edges.where(F.col("kind") == kind).select("unit_id", F.col("src").alias("node_id"))
    ends = nodes.join(left, ["unit_id", "node_id"], "left_anti")
    if persisting:
        ends = ends.where(~F.coalesce(F.array_contains("labels", "Rollback"), F.lit(False)))
    return ends.select("unit_id", "node_id")
