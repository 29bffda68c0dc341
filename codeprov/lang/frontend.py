"""From source text to a code property graph: wrappers, levels, canonical text, nodes and edges."""

from __future__ import annotations

import copy
import re

from codeprov.lang import parse as P
from codeprov.lang.lexer import tokens
from codeprov.lang.parse import Node

_STATEMENTS = frozenset("If Loop Return Rollback Expression Declaration EmitEvent SpecialBlock Block Placeholder Jump Empty".split())
_MEMBERS = frozenset("Function Field Event Modifier Struct Enum Using".split())


def level_of(code: str) -> str | None:
    """unit, function or statement: the outermost thing that a text declares; null if it cannot be read."""
    try:
        kinds = {n.kind for n in P.parse(code).children}
    except (P.SyntaxProblem, RecursionError):
        return None
    if "Record" in kinds:
        return "unit"
    if kinds & {"Function", "Modifier"}:
        return "function"
    return "statement" if kinds - {"Pragma"} else None


def parseable(code: str, mode: str = "lenient") -> bool:
    return P.parses(code, mode)


def infer_wrappers(root: Node) -> Node:
    """Members without a unit get one, statements without a function get one; both are marked as inferred."""
    loose = [n for n in root.children if n.kind not in ("Record", "Pragma")]
    if loose:
        record = Node("Record", loose[0].line, "", props={"kind": "contract", "inferred": True})
        body = Node("Block", loose[0].line)
        for n in loose:
            if n.kind in _MEMBERS:
                record.add("FIELD" if n.kind == "Field" else "MEMBER", n)
            else:
                body.add("STATEMENT", n)
        if body.children:
            f = Node("Function", body.line, "inferred", props={"words": ["public"], "modifiers": [], "default": False, "inferred": True})
            f.add("BODY", body)
            record.add("MEMBER", f)
        root.children = [n for n in root.children if n.kind in ("Record", "Pragma")] + [record]
        root.roles = {"MEMBER": list(root.children)}
    for r in root.children:
        if r.kind == "Record":
            stray = [m for m in r.all("MEMBER") if m.kind in _STATEMENTS]
            if stray:
                f = Node("Function", stray[0].line, "inferred", props={"words": ["public"], "modifiers": [], "default": False, "inferred": True})
                b = Node("Block", stray[0].line)
                for s in stray:
                    b.add("STATEMENT", s)
                f.add("BODY", b)
                keep = [m for m in r.children if m not in stray]
                r.children, r.roles["MEMBER"] = [*keep, f], [m for m in r.all("MEMBER") if m not in stray] + [f]
    return root


def expand_modifiers(root: Node) -> Node:
    """Each applied modifier's body, copied afresh, around the function's body at every placeholder; the first named is outermost."""
    for record in (n for n in root.children if n.kind == "Record"):
        known = {m.name: m for m in record.all("MEMBER") if m.kind == "Modifier"}
        for f in (m for m in record.all("MEMBER") if m.kind == "Function" and m.get("BODY")):
            body = f.get("BODY")
            for name, _ in reversed(f.props["modifiers"]):
                if name in known and known[name].get("BODY"):
                    body = _filled(copy.deepcopy(known[name].get("BODY")), body)
            if body is not f.get("BODY"):
                f.children = [body if c is f.get("BODY") else c for c in f.children]
                f.roles["BODY"] = [body]
    return root


def _filled(n: Node, body: Node) -> Node:
    """``n`` with each placeholder below it replaced by a copy of ``body``."""
    stack = [n]
    while stack:
        x = stack.pop()
        swap = {id(c): copy.deepcopy(body) for c in x.children if c.kind == "Placeholder"}
        if swap:
            x.children = [swap.get(id(c), c) for c in x.children]
            x.roles = {k: [swap.get(id(c), c) for c in v] for k, v in x.roles.items()}
        stack += [c for c in x.children if id(c) not in {id(y) for y in swap.values()}]
    return n


# -- the source profile of the clone finder


def strip_layout(code: str) -> str:
    return "".join(t.text for t in tokens(code))


_KEEP = frozenset("msg block tx now this super sender value data origin timestamp number difficulty coinbase gaslimit transfer send call delegatecall callcode staticcall balance push length require assert revert throw selfdestruct suicide keccak256 sha3 sha256 ripemd160 ecrecover blockhash gas abi encode encodePacked if else for while do return returns new delete emit true false wei ether finney szabo seconds minutes hours days weeks years storage memory calldata unchecked assembly payable break continue _".split())


def canonical_parts(code: str, names: str = "canonical", literals: str = "mask", numbers: str = "keep", drop_visibility: bool = True) -> list[list[str]]:
    """Tokens of each function, constructor and modifier, names replaced by what they are.

    Units are c, libraries l, functions f, modifiers m; variables and parameters stand for their declared
    type, or uint without one. State variables and events give no tokens; dots stay, brackets go.
    """
    root = infer_wrappers(P.parse(code))
    plain = tokens(code)
    kinds: dict[str, str] = {}
    for n in root.walk():
        if n.kind in ("Field", "Variable", "Parameter", "StructField") and n.name:
            kinds[n.name] = re.sub(r"\W+", "", n.props.get("type", "uint")) or "uint"
    for n in root.walk():
        if n.kind == "Function" and n.name not in ("", "constructor", "inferred"):
            kinds[n.name] = "f"
        elif n.kind == "Modifier":
            kinds[n.name] = "m"
        elif n.kind == "Record" and n.name:
            kinds[n.name] = "l" if n.props["kind"] == "library" else "c"

    def word(t, before: str) -> str | None:
        if t.kind == "string":
            return "stringLiteral" if literals == "mask" else t.text
        if t.kind == "number":
            return "0" if numbers == "mask" else t.text
        if t.kind == "sign":
            return None if t.text in "(){}[],;" else t.text
        if drop_visibility and t.text in P.VISIBILITY:
            return None
        if names != "canonical" or t.text in _KEEP or P.is_elementary(t.text) or before == "." and t.text not in kinds or t.text in ("function", "modifier", "constructor", "fallback", "receive"):
            return t.text
        return kinds.get(t.text, "uint")

    parts, loose, i = [], [], 0
    while i < len(plain):
        t = plain[i]
        if t.text in ("contract", "library", "interface", "abstract") and i + 1 < len(plain) and plain[i + 1].kind == "name":
            while i < len(plain) and plain[i].text != "{":
                i += 1
            i += 1
            continue
        if t.text in ("function", "constructor", "modifier", "fallback", "receive") and t.kind == "name":
            row, depth, before = [], 0, ""
            while i < len(plain):
                t = plain[i]
                w = word(t, before)
                if w is not None:
                    row.append(w)
                before = t.text
                depth += (t.text == "{") - (t.text == "}")
                i += 1
                if t.text == "}" and depth == 0 or t.text == ";" and depth == 0:
                    break
            parts.append(row)
            continue
        if t.text in ("event", "struct", "enum", "using", "pragma", "import", "error") and t.kind == "name":
            depth = 0
            while i < len(plain):
                depth += (plain[i].text == "{") - (plain[i].text == "}")
                i += 1
                if plain[i - 1].text == ";" and depth == 0 or plain[i - 1].text == "}" and depth == 0:
                    break
            continue
        if t.text == "}":
            i += 1
            continue
        row, before, depth, start = [], "", 0, i
        while i < len(plain):
            t = plain[i]
            if depth == 0 and i > start and t.text in ("function", "constructor", "modifier", "contract", "library") and t.kind == "name":
                break
            w = word(t, before)
            if w is not None:
                row.append(w)
            before = t.text
            depth += (t.text == "{") - (t.text == "}")
            i += 1
            if depth <= 0 and t.text in ";}":
                break
        text = plain[start:i]
        declared = any(n.kind == "Field" and n.line == text[0].line for r in root.children if r.kind == "Record" for n in r.all("FIELD"))
        if not declared:
            loose += row
    return [p for p in parts if p] + ([loose] if loose else [])


def canonical_text(code: str) -> str | None:
    try:
        return " ; ".join(" ".join(p) for p in canonical_parts(code))
    except (P.SyntaxProblem, RecursionError):
        return None


def clone_type(q: str, t: str) -> str | None:
    """I or II of two texts; a score decides about III."""
    if q is None or t is None:
        return None
    if strip_layout(q) == strip_layout(t):
        return "I"
    return "II" if canonical_text(q) is not None and canonical_text(q) == canonical_text(t) else None


# -- the graph


class Graph:
    """Nodes (id = place in ``nodes``) and edges of one unit; edges by kind in both directions."""

    KINDS = ("AST", "EOG", "DFG", "REFERS_TO", "INVOKES")

    def __init__(self) -> None:
        self.nodes: list[Node] = []
        self.labels: list[set[str]] = []
        self.fn: list[int] = []
        self.parent: list[int] = []
        self.out = {k: {} for k in self.KINDS}
        self.inn = {k: {} for k in self.KINDS}
        self.roles: list[tuple[int, int, str]] = []
        self.version: tuple[int, int] | None = None
        self.safe: set[int] = set()

    def new(self, n: Node, label: str, fn: int, parent: int) -> int:
        self.nodes.append(n)
        self.labels.append({label})
        self.fn.append(fn)
        self.parent.append(parent)
        return len(self.nodes) - 1

    def edge(self, kind: str, a: int, b: int) -> None:
        self.out[kind].setdefault(a, set()).add(b)
        self.inn[kind].setdefault(b, set()).add(a)

    def reach(self, sources, kind: str, reverse: bool = False, max_hops: int | None = None, avoid=frozenset()) -> set[int]:
        """What the sources reach in one or more steps."""
        step = (self.inn if reverse else self.out)[kind]
        seen: set[int] = set()
        front = set(sources)
        hops = 0
        while front and (max_hops is None or hops < max_hops):
            front = {b for a in front for b in step.get(a, ()) if b not in seen and b not in avoid}
            seen |= front
            hops += 1
        return seen

    def of(self, label: str) -> list[int]:
        return [i for i, x in enumerate(self.labels) if label in x]

    def name(self, i: int) -> str:
        return self.nodes[i].name

    def rows(self) -> tuple[list[tuple], list[tuple]]:
        """Node rows (id, labels, name, type, line, props) and edge rows (src, dst, kind)."""
        nodes = [(i, sorted(self.labels[i]), n.name, n.props.get("type", ""), n.line, {k: str(v) for k, v in n.props.items() if k not in ("type", "modifiers")}) for i, n in enumerate(self.nodes)]
        edges = [(a, b, k) for k in self.KINDS for a, bs in self.out[k].items() for b in sorted(bs)] + self.roles
        return nodes, edges


def graph_of(code: str, infer: bool = True, expand: bool = True, indirect_flow: bool = True, version: str | None = None) -> Graph:
    """Parse, wrap, expand and run the passes; the options are the ablations."""
    root = P.parse(code)
    if infer:
        root = infer_wrappers(root)
    if expand:
        root = expand_modifiers(root)
    from codeprov.graph import passes

    return passes.build(root, indirect_flow, version)
