"""Every registered workload against its SQL at the smallest size; the others must give rows."""

import pytest
from codeprov.oracles import SQL
from codeprov.queries import QUERIES

from tests import oracle

SF = "/root/testdata/sf0.001"
#: No row meets the condition at this size.
EMPTY = {"O_theta", "O_self_join"}


@pytest.fixture(scope="module")
def con():
    return oracle.connect(SF)


@pytest.mark.parametrize("key", sorted(SQL))
def test_equals_sql(spark, con, key):
    said = oracle.difference(spark, con, SF, QUERIES[key], SQL[key])
    assert said is None or said == "no rows" and key in EMPTY


def test_tools_table(spark):
    rows = {(r.tool, r.category): r for r in QUERIES["W25_rule_by_tool_table"](spark, SF).collect()}
    full = rows["full", "total"]
    assert (full.tp, full.fp) == (full.labels, 0)
    for tool in ("no mitigations", "no relevancy"):
        assert rows[tool, "total"].tp == full.tp and rows[tool, "total"].fp >= full.fp
    assert rows["no mitigations", "total"].fp > 0 and rows["lexical", "total"].fp > 0
    assert rows["lexical", "total"].tp < full.tp


def test_fragments_lose_recall_before_precision(spark):
    r = {x.level: x for x in QUERIES["W26_functions_statements"](spark, SF).collect()}
    assert r["unit"].rec >= r["function"].rec >= r["statement"].rec > 0.2
    assert min(x.prec for x in r.values()) >= 0.9


def test_study_narrows_down(spark):
    n = {x.step: x.disseminator for x in QUERIES["W28_reuse_study"](spark, SF).collect()}
    assert n["snippets"] >= n["weak snippets"] >= n["weak snippets with clones"] >= n["weak snippets with later clones"] >= n["validated snippets"] > 0
    assert n["candidate units"] >= n["candidate codes"] >= n["validated codes"] > 0


def test_review_has_eight_cells(spark):
    assert QUERIES["W30_review_sample"](spark, SF).count() == 8


def test_clone_classes(spark):
    rows = QUERIES["W08_class_tp_fp"](spark, SF).collect()
    assert len(rows) == 17 and sum(r.tp for r in rows) > 0


def test_two_phases_resolve_more_with_a_schedule(spark):
    rows = QUERIES["W22_two_phase"](spark, SF).collect()
    assert {r.status for r in rows} <= {"ok", "budget_exceeded"} and any(r.phase == 0 for r in rows if r.phase is not None)


def test_no_cartesian_product_in_the_flagship(spark):
    plan = QUERIES["W01_clone_search"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan


def test_all_pairs_and_full_join_leave_no_document_out(spark, con):
    ids = {x for (x,) in con.execute("SELECT doc_id FROM documents").fetchall()}
    items = con.execute("SELECT count(*) FROM benchmark WHERE item_id % 100 = 0").fetchone()[0]
    scores = QUERIES["W10_bruteforce_scores"](spark, SF).collect()
    assert {r.doc_id for r in scores} == ids and len(scores) == items * len(ids)
    best = {(r.item_id, r.doc_id): r.score for r in scores}
    clones = [r for r in QUERIES["W01_clone_search"](spark, SF).collect() if r.item_id % 100 == 0]
    assert all(best[r.item_id, r.doc_id] == r.score for r in clones)
    joined = QUERIES["O_join_full"](spark, SF).collect()
    assert {r.doc_id for r in joined} == ids and {r.doc_id for r in joined if r.lang is not None} == {x for (x,) in con.execute("SELECT doc_id FROM documents WHERE lang IS NOT NULL").fetchall()}
