"""The passes that turn a tree into a code property graph: nodes, references, evaluation order, data flow."""

from __future__ import annotations

import re

from codeprov.lang.frontend import Graph
from codeprov.lang.parse import Node

#: Names of the language that are no variables.
_KNOWN = frozenset("now this super msg tx block true false keccak256 sha3 sha256 blockhash require assert revert selfdestruct suicide abi address uint uint256 int bool bytes32 bytes string ecrecover".split())
GUARDS = frozenset(("require", "assert"))
ROLLBACKS = frozenset(("revert", "throw"))
_BUILTIN_BASES = frozenset(("msg", "tx", "block"))


class _Scope:
    def __init__(self, up: _Scope | None = None) -> None:
        self.up, self.names = up, {}

    def find(self, name: str) -> int | None:
        s = self
        while s is not None:
            if name in s.names:
                return s.names[name]
            s = s.up
        return None


def build(root: Node, indirect_flow: bool = True, version: str | None = None) -> Graph:
    g = Graph()
    text = version or next((n.props.get("text", "") for n in root.children if n.kind == "Pragma" and n.props.get("text")), "")
    found = re.search(r"(\d+)\.(\d+)", text)
    g.version = (int(found[1]), int(found[2])) if found else None
    records = [n for n in root.children if n.kind == "Record"]
    others = [n for n in root.children if n.kind not in ("Record", "Pragma")]
    if others:
        bare = Node("Record", others[0].line, props={"kind": "contract"})
        for n in others:
            if n.kind in ("Function", "Field", "Modifier"):
                bare.add("FIELD" if n.kind == "Field" else "MEMBER", n)
        if bare.children:
            records.append(bare)
    for r in records:
        _record(g, r, indirect_flow)
    return g


def _record(g: Graph, r: Node, indirect: bool) -> None:
    rid = g.new(r, "Record", -1, -1)
    if r.props.get("inferred"):
        g.labels[rid].add("Inferred")
    scope = _Scope()
    for f in r.all("FIELD"):
        i = g.new(f, "Field", -1, rid)
        g.edge("AST", rid, i)
        g.roles.append((rid, i, "FIELD"))
        scope.names[f.name] = i
    functions: dict[str, int] = {}
    todo = []
    for m in r.all("MEMBER"):
        if m.kind == "Function":
            i = g.new(m, "Function", len(g.nodes), rid)
            g.fn[i] = i
            g.edge("AST", rid, i)
            if m.props.get("inferred"):
                g.labels[i].add("Inferred")
            if m.name == "constructor" or m.name and m.name == r.name:
                g.labels[i].add("Constructor")
            elif not set(m.props["words"]) & {"private", "internal"} and r.props.get("kind") != "library":
                g.labels[i].add("Public")
            if r.props.get("kind") == "library":
                g.safe.add(i)
            functions.setdefault(m.name, i)
            todo.append((m, i))
        elif m.kind in ("Struct", "Event", "Enum"):
            i = g.new(m, m.kind, -1, rid)
            g.edge("AST", rid, i)
    for m, i in todo:
        _Function(g, i, functions, scope, indirect).run(m)
    # What a field is given flows to every read of it; constructor values too.
    for f in r.all("FIELD"):
        i = scope.names[f.name]
        if f.get("INITIALIZER") is not None:
            walker = _Function(g, i, functions, scope, indirect)
            walker.fn = -1
            got, _ = walker.expression(f.get("INITIALIZER"), set(), i)
            g.edge("DFG", got, i)


class _Function:
    def __init__(self, g: Graph, fid: int, functions: dict[str, int], scope: _Scope, indirect: bool) -> None:
        self.g, self.fn, self.functions, self.scope, self.indirect = g, fid, functions, _Scope(scope), indirect
        self.unchecked = False
        #: Undeclared names of incomplete code count as fields that were left out.
        self.fields = scope
        self.partial = any("Record" in g.labels[i] and "Inferred" in g.labels[i] for i in range(len(g.nodes)))

    def run(self, m: Node) -> None:
        g = self.g
        for p in m.all("PARAMETER"):
            i = g.new(p, "Parameter", self.fn, self.fn)
            g.edge("AST", self.fn, i)
            if p.name:
                self.scope.names[p.name] = i
        for p in m.all("RETURNS"):
            if p.name:
                i = g.new(p, "Variable", self.fn, self.fn)
                g.edge("AST", self.fn, i)
                self.scope.names[p.name] = i
        if m.get("BODY") is not None:
            front = self.statement(m.get("BODY"), {self.fn}, self.fn)
            if front:
                self.follow(self.make(Node("Exit", m.line), "Exit", self.fn), front)

    def make(self, n: Node, label: str, parent: int) -> int:
        i = self.g.new(n, label, self.fn, parent)
        self.g.edge("AST", parent, i)
        if self.unchecked:
            self.g.labels[i].add("Unchecked")
        return i

    def follow(self, i: int, front: set[int]) -> set[int]:
        for a in front:
            self.g.edge("EOG", a, i)
        return {i}

    # -- statements: the nodes after which evaluation goes on
    def statement(self, n: Node, front: set[int], parent: int) -> set[int]:
        g, k = self.g, n.kind
        if k == "Block":
            i = self.make(n, "Block", parent)
            outer, self.scope = self.scope, _Scope(self.scope)
            for s in n.children:
                front = self.statement(s, front, i)
            self.scope = outer
            return front
        if k == "Expression":
            _, front = self.expression(n.get("VALUE"), front, parent)
            return front
        if k == "Declaration":
            ids = []
            for v in n.all("VARIABLE"):
                i = self.make(v, "Variable", parent)
                self.scope.names[v.name] = i
                ids.append(i)
            if n.get("INITIALIZER") is not None:
                value, front = self.expression(n.get("INITIALIZER"), front, parent)
                for i in ids:
                    g.edge("DFG", value, i)
            for i in ids:
                front = self.follow(i, front)
            return front
        if k == "If":
            i = self.make(n, "If", parent)
            c, front = self.expression(n.get("CONDITION"), front, i)
            g.edge("DFG", c, i)
            g.roles.append((i, c, "CONDITION"))
            g.labels[i].add("Branch")
            front = self.follow(i, front)
            then = self.statement(n.get("THEN"), set(front), i)
            other = self.statement(n.get("ELSE"), set(front), i) if n.get("ELSE") is not None else front
            return then | other
        if k == "Loop":
            outer, self.scope = self.scope, _Scope(self.scope)
            i = self.make(n, "Loop", parent)
            if n.get("INIT") is not None:
                front = self.statement(n.get("INIT"), front, i)
            front = self.follow(i, front)
            if n.get("CONDITION") is not None:
                c, front = self.expression(n.get("CONDITION"), front, i)
                g.edge("DFG", c, i)
                g.roles.append((i, c, "CONDITION"))
            after = set(front)
            back = self.statement(n.get("BODY"), front, i)
            if n.get("STEP") is not None:
                _, back = self.expression(n.get("STEP"), back, i)
            for a in back:
                g.edge("EOG", a, i)
            self.scope = outer
            return after
        if k == "Return":
            i = self.make(n, "Return", parent)
            if n.get("VALUE") is not None:
                v, front = self.expression(n.get("VALUE"), front, i)
                g.edge("DFG", v, i)
                g.edge("DFG", i, self.fn)
            self.follow(i, front)
            return set()
        if k == "Rollback":
            self.follow(self.make(n, "Rollback", parent), front)
            return set()
        if k == "EmitEvent":
            i = self.make(n, "EmitEvent", parent)
            v, front = self.expression(n.get("VALUE"), front, i)
            return self.follow(i, front)
        if k == "SpecialBlock":
            i = self.make(n, "SpecialBlock", parent)
            front = self.follow(i, front)
            if n.get("BODY") is not None:
                self.unchecked, before = n.name == "unchecked" or self.unchecked, self.unchecked
                front = self.statement(n.get("BODY"), front, i)
                self.unchecked = before
            return front
        return front

    # -- expressions: their node, and the nodes after which evaluation goes on
    def expression(self, n: Node, front: set[int], parent: int) -> tuple[int, set[int]]:
        g, k = self.g, n.kind
        if k == "Reference":
            i = self.make(n, "Reference", parent)
            to = self.scope.find(n.name)
            if to is None and self.partial and n.name not in _KNOWN and n.name not in self.functions and not n.props.get("callee"):
                to = self.g.new(Node("Field", n.line, n.name, props={"type": n.props.get("used", "uint"), "words": []}), "Field", -1, -1)
                g.labels[to].add("Inferred")
                self.fields.names[n.name] = to
            if to is not None:
                g.edge("REFERS_TO", i, to)
                g.edge("DFG", to, i)
            elif n.name == "now":
                g.labels[i].add("Builtin")
            return i, self.follow(i, front)
        if k == "Literal":
            i = self.make(n, "Literal", parent)
            return i, self.follow(i, front)
        if k == "Assign":
            i = self.make(n, "Assign", parent)
            right, front = self.expression(n.get("RHS"), front, i)
            left, front = self.expression(n.get("LHS"), front, i)
            g.edge("DFG", right, i)
            if n.name != "=":
                g.edge("DFG", left, i)
            g.roles += [(i, left, "LHS"), (i, right, "RHS")]
            self.write(left, i)
            return i, self.follow(i, front)
        if k == "UnaryOp":
            i = self.make(n, "UnaryOp", parent)
            o, front = self.expression(n.get("OPERAND"), front, i)
            g.edge("DFG", o, i)
            if n.name in ("++", "--", "delete"):
                self.write(o, i)
            return i, self.follow(i, front)
        if k == "Call":
            return self.call(n, front, parent)
        i = self.make(n, k, parent)
        if k == "Index" and n.get("BASE") is not None:
            inner = n.get("BASE")
            if inner.kind == "Reference":
                inner.props.setdefault("used", "mapping(address=>uint)")
            elif inner.kind == "Index" and inner.get("BASE") is not None and inner.get("BASE").kind == "Reference":
                inner.get("BASE").props["used"] = "mapping(address=>mapping(address=>uint))"
        if k == "Member" and n.get("BASE").kind == "Reference" and n.get("BASE").name in _BUILTIN_BASES and self.scope.find(n.get("BASE").name) is None:
            n.name = f"{n.get('BASE').name}.{n.name}"
            g.labels[i].add("Builtin")
            return i, self.follow(i, front)
        for role, kids in n.roles.items():
            for c in kids:
                x, front = self.expression(c, front, i) if c.kind != "CallOption" else self.expression(c.get("VALUE"), front, i)
                g.edge("DFG", x, i)
                g.roles.append((i, x, role))
        return i, self.follow(i, front)

    def write(self, target: int, value: int) -> None:
        """``value`` flows to the variable or field below ``target``; the place written is marked."""
        g, i = self.g, target
        g.labels[value].add("Write")
        while True:
            refs = g.out["REFERS_TO"].get(i)
            if refs:
                for d in refs:
                    g.edge("DFG", value, d)
                    g.nodes[value].props.setdefault("writes", set()).add(d)
                return
            g.edge("DFG", value, i)
            base = next((b for a, b, r in reversed(g.roles) if a == i and r == "BASE"), None)
            if base is None:
                kids = [b for a, b, r in g.roles if a == i and r == "ARG"]
                for b in kids:
                    self.write(b, value)
                return
            i = base

    def call(self, n: Node, front: set[int], parent: int) -> tuple[int, set[int]]:
        g = self.g
        i = self.make(n, "Call", parent)
        callee = n.get("CALLEE")
        options: dict[str, int] = {}
        at = callee
        # Value and gas as options in braces, or as the older calls that stand between.
        while at is not None:
            if at.kind == "Options":
                for o in at.all("OPTION"):
                    v, front = self.expression(o.get("VALUE"), front, i)
                    options[o.name] = v
                    g.edge("DFG", v, i)
                at = at.get("BASE")
            elif at.kind == "Call" and at.get("CALLEE") is not None and at.get("CALLEE").kind == "Member" and at.get("CALLEE").name in ("value", "gas"):
                for a in at.all("ARG"):
                    v, front = self.expression(a, front, i)
                    options[at.get("CALLEE").name] = v
                    g.edge("DFG", v, i)
                at = at.get("CALLEE").get("BASE")
            else:
                break
        name = at.name if at is not None else ""
        n.name = name
        n.props["options"] = sorted(options)
        n.props["option_ids"] = options
        if at is not None and at.kind == "Reference":
            at.props["callee"] = True
        if at is not None and at.kind == "Member" and at.get("BASE") is not None:
            if at.get("BASE").kind == "Reference" and name in ("transfer", "send", "call", "delegatecall", "callcode"):
                at.get("BASE").props["used"] = "address"
            b, front = self.expression(at.get("BASE"), front, i)
            g.edge("DFG", b, i)
            g.roles.append((i, b, "BASE"))
            n.props["base"] = b
        elif at is not None and at.kind not in ("Reference", "Member"):
            b, front = self.expression(at, front, i)
            g.edge("DFG", b, i)
        args = []
        for a in n.all("ARG"):
            v, front = self.expression(a, front, i)
            args.append(v)
            g.edge("DFG", v, i)
            g.roles.append((i, v, "ARG"))
        n.props["args"] = args
        if name == "push" and "base" in n.props:
            self.write(n.props["base"], i)
        own = self.functions.get(name) if at is not None and at.kind == "Reference" else None
        if own is not None:
            g.edge("INVOKES", i, own)
            g.edge("DFG", own, i)
            wanted = [j for j in g.out["AST"].get(own, ()) if "Parameter" in g.labels[j]]
            for v, p in zip(args, sorted(wanted), strict=False):
                g.edge("DFG", v, p)
        front = self.follow(i, front)
        if name in GUARDS:
            g.labels[i].add("Branch")
            self.follow(self.make(Node("Rollback", n.line, name), "Rollback", i), front)
        if name in ROLLBACKS and own is None:
            g.labels[i].add("Rollback")
            return i, set()
        if self.indirect and name in ("transfer", "send", "call") and "base" in n.props:
            # The balance that is paid out depends on who asks: a flow that no assignment shows.
            g.labels[i].add("MoneyFlow")
        return i, front
