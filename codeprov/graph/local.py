"""Backend B: all rules on a unit in one task. Units are small and no edge leaves one, so nothing is shuffled."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame

from codeprov.graph import rules as R
from codeprov.lang import frontend, parse

FINDINGS = "unit_id long, rule_id string, category string, line int, node_id int, phase int, status string"


def findings_of(code: str | None, wanted=None, budget: int | None = None, hop_schedule: tuple[int, ...] = (), use_relevancy: bool = True, use_mitigations: bool = True, infer: bool = True, expand: bool = True, indirect_flow: bool = True, version: str | None = None):
    """Findings, the phase that settled them, and ok, budget_exceeded or error (a text that cannot be read is an error).

    Phase 0 searches in full under the budget; each later phase cuts positive searches to the next number of
    hops of the schedule. Mitigations are never cut.
    """
    chosen = R.RULES if wanted is None else [R.BY_ID[r] for r in wanted]
    try:
        g = frontend.graph_of(code or "", infer, expand, indirect_flow, version)
    except (parse.SyntaxProblem, RecursionError):
        return [], 0, "error"
    found, status, phase = [], "ok", 0
    for phase, hops in enumerate((None, *hop_schedule)):
        found, status = R.check(g, chosen, hops, use_relevancy, use_mitigations, budget)
        if status == "ok":
            break
    return found, phase, status


def evaluate_units(units: DataFrame, id: str = "unit_id", code: str = "code", rules: str | None = None, **options) -> DataFrame:
    """Findings of every unit; with ``rules`` (a column of arrays of rule ids) only those of the row.

    A unit without a finding gives one row with null rule if its status is not ok, else none.
    """
    src = units.selectExpr(f"`{id}` AS unit_id", f"`{code}` AS code", *([f"`{rules}` AS wanted"] if rules else []))

    def work(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            rows = []
            for r in b.itertuples(index=False):
                found, phase, status = findings_of(r.code, list(r.wanted) if rules else None, **options)
                rows += [(r.unit_id, rule, cat, line, node, phase, status) for rule, cat, line, node in found]
                if not found and status != "ok":
                    rows.append((r.unit_id, None, None, None, None, phase, status))
            yield pd.DataFrame(rows, columns=["unit_id", "rule_id", "category", "line", "node_id", "phase", "status"])

    return src.mapInPandas(work, FINDINGS)


def graph_tables(units: DataFrame, id: str = "unit_id", code: str = "code", **options) -> tuple[DataFrame, DataFrame]:
    """``cpg_nodes`` and ``cpg_edges`` of every readable unit, for SQL users and for backend A."""
    src = units.selectExpr(f"`{id}` AS unit_id", f"`{code}` AS code")

    def run(edges: bool):
        def work(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for b in batches:
                rows = []
                for r in b.itertuples(index=False):
                    try:
                        nodes, links = frontend.graph_of(r.code or "", **options).rows()
                    except (parse.SyntaxProblem, RecursionError):
                        continue
                    rows += [(r.unit_id, *x) for x in (links if edges else nodes)]
                yield pd.DataFrame(rows, columns=["unit_id", "src", "dst", "kind"] if edges else ["unit_id", "node_id", "labels", "name", "type", "line", "props"])

        return work

    return (
        src.mapInPandas(run(False), "unit_id long, node_id long, labels array<string>, name string, type string, line int, props map<string,string>"),
        src.mapInPandas(run(True), "unit_id long, src long, dst long, kind string"),
    )
