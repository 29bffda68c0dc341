import random

import pytest
from codeprov.corpus import templates as T
from codeprov.graph import closure, local, model, pattern, rules, validate
from codeprov.graph.passes import build
from codeprov.lang import frontend, parse
from codeprov.lang.frontend import graph_of


@pytest.mark.parametrize("i", range(len(T.TEMPLATES)))
def test_each_template_gives_its_finding_and_no_other(i):
    t = T.TEMPLATES[i]
    for m in range(len(T.MUTATIONS)):
        code = T.render(i, m)
        assert parse.parses(code, "strict")
        got = [(r, line) for r, _, line, _ in rules.check(graph_of(code))[0]]
        assert got == ([(t.rule_id, T.weak_line(code))] if t.weak else [])


def test_seventeen_rules_in_ten_categories():
    from codeprov.measure.funnel import CATEGORIES

    assert len(rules.RULES) == 17 and {r.category for r in rules.RULES} == set(CATEGORIES)


def test_switching_parts_off_never_loses_findings():
    for i in range(len(T.TEMPLATES)):
        g = graph_of(T.render(i))
        full = set(rules.check(g)[0])
        assert full <= set(rules.check(g, use_mitigations=False)[0]) and full <= set(rules.check(g, use_relevancy=False)[0])


def test_fewer_hops_never_add_base_matches():
    for i in range(0, len(T.TEMPLATES), 2):
        g = graph_of(T.render(i))
        sizes = [len(rules.check(g, hops=h, use_mitigations=False)[0]) for h in (1, 2, 4, 16, None)]
        assert sizes == sorted(sizes)


def test_condition_graph():
    g = graph_of("contract A { address chief; function f() public { if (msg.sender == chief) { chief = msg.sender; } } }")
    order = sorted(g.reach([g.of("Function")[0]], "EOG"))
    names = [g.name(i) for i in order]
    branch = g.of("Branch")[0]
    eq = next(i for i in g.of("BinaryOp"))
    assert names.index("msg.sender") >= 0 and eq in g.inn["DFG"][branch] and len(g.inn["DFG"][eq]) == 2
    assert {r for _, _, r in g.roles} >= {"LHS", "RHS", "CONDITION"}


def test_modifier_bodies_are_fresh_copies():
    code = "contract A { uint n; modifier twice() { n = 1; _; _; } function a() public twice { n = 2; } function b() public twice { n = 3; } }"
    g = graph_of(code)
    writes = [i for i in g.of("Assign")]
    assert len(writes) == 2 * (1 + 2)
    plain = graph_of(code, expand=False)
    assert len(plain.of("Assign")) == 2


def test_wrappers_and_levels():
    assert [frontend.level_of(x) for x in ("contract A { }", "function f() { }", "x = 1", "")] == ["unit", "function", "statement", None]
    g = graph_of("x = y + 1")
    assert "Inferred" in g.labels[g.of("Record")[0]] and "Inferred" in g.labels[g.of("Function")[0]]
    assert not build(parse.parse("x = y + 1")).nodes


def test_lenient_and_strict():
    for text in ("x = a + 1\ny = 2", "if (a) {\n  ...\n}", "function f(uint a) { a = 1 }", "msg.sender.transfer(1)"):
        assert parse.parses(text) and not parse.parses(text, "strict")
    for broken in ("function (((", "}{", "contract {", "(" * 3000, '"open', "/* never closed"):
        assert isinstance(parse.parses(broken), bool)
        assert local.findings_of(broken)[2] in ("ok", "error")


def test_parameters_that_persist():
    g = graph_of("contract A { uint s; function f(uint a, uint b) public { uint c = a; s = c; } }")
    assert [g.name(i) for i in rules.persisted_parameters(g)] == ["a"]


def test_budget_and_schedule():
    code = "contract A { uint t; function f(uint a) public {\n" + "\n".join(f"uint v{i} = {'a' if i == 0 else f'v{i - 1}'};" for i in range(64)) + "\nt = t + v63;\n} }"
    assert local.findings_of(code)[1:] == (0, "ok")
    assert local.findings_of(code, budget=50)[2] == "budget_exceeded"
    found, phase, status = local.findings_of(code, wanted=["AR1"], budget=90, hop_schedule=(8, 2))
    assert status == "ok" and phase > 0


def test_phases_follow_what_a_search_forms(spark):
    """A chain of n edges from one source forms min(n, hops) pairs."""
    chains = {1: 3, 2: 6, 3: 40}
    edges = spark.createDataFrame([(u, i, i + 1, "DFG") for u, n in chains.items() for i in range(n)], "unit_id long, src long, dst long, kind string")
    nodes = spark.createDataFrame([(u, i) for u, n in chains.items() for i in range(n + 1)], "unit_id long, node_id long")
    starts = spark.createDataFrame([(u, 0) for u in chains], "unit_id long, node_id long")
    formed = {(r.unit_id, r.hops): r.pairs for r in closure.formed(edges, "DFG", starts, 5).collect()}
    assert formed[1, 3] == 3 and formed[2, 6] == 6 and formed[3, 6] == 6 and (3, 7) not in formed
    rule = pattern.Rule("X", "x", lambda n, e, hops: closure.reach(e, "DFG", starts, hops).select("unit_id", "src", "dst"), ("src", "dst"))
    found, status = validate.two_phase(nodes, edges, [rule], "DFG", starts, 5, (4, 2))
    assert {r.unit_id: (r.phase, r.status) for r in status.collect()} == {1: (0, "ok"), 2: (1, "ok"), 3: (1, "ok")}
    assert {r.unit_id: r["count"] for r in found.groupBy("unit_id").count().collect()} == {1: 3, 2: 4, 3: 4}
    assert {r.status for r in validate.two_phase(nodes, edges, [rule], "DFG", starts, 1, ())[1].collect()} == {"budget_exceeded"}


def test_closure_against_enumeration(spark):
    rng = random.Random(4)
    edges = sorted({(1, rng.randrange(8), rng.randrange(8), "EOG") for _ in range(14)})
    e = spark.createDataFrame(edges, "unit_id long, src long, dst long, kind string")
    s = spark.createDataFrame([(1, 0)], "unit_id long, node_id long")
    got = {r.dst: r.hops for r in closure.reach(e, "EOG", s).collect()}
    want, front, hops = {}, {0}, 0
    while front:
        hops += 1
        front = {b for _, a, b, _ in edges if a in front} - set(want)
        want |= dict.fromkeys(front, hops)
    assert got == want
    for dst in range(8):
        assert (closure.trails(e, "EOG", 0, dst, 8).count() > 0) == (dst in want)
    avoid = spark.createDataFrame([(1, 3)], "unit_id long, node_id long")
    assert 3 not in {r.dst for r in closure.reach(e, "EOG", s, avoid=avoid).collect()}


def test_stored_graph_equals_local_reach(spark, tmp_path):
    units = spark.createDataFrame([(i, T.render(i)) for i in range(6)], "unit_id long, code string")
    nodes, edges = local.graph_tables(units)
    model.save(nodes, edges, str(tmp_path), 4)
    n2, e2 = model.load(spark, str(tmp_path))
    assert n2.count() == nodes.count()
    source = n2.where("array_contains(labels, 'Parameter')").select("unit_id", "node_id")
    got = {(r.unit_id, r.src, r.dst) for r in closure.reach(e2, "DFG", source).collect()}
    want = set()
    for i in range(6):
        g = graph_of(T.render(i))
        want |= {(i, p, d) for p in g.of("Parameter") for d in g.reach([p], "DFG")}
    assert got == want
