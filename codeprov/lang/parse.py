"""A lenient parser: what the grammar allows only inside something else may also stand alone.

``lenient`` lets members, statements and expressions start a text, lets a line break end a statement, skips
left-out code, and recovers after what it cannot read. ``strict`` takes complete sources only.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from codeprov.lang.lexer import CONTINUES, Token, tokens

ELEMENTARY = ("uint", "int", "address", "bool", "string", "bytes", "byte", "fixed", "ufixed", "mapping", "var", "function")
VISIBILITY = frozenset("public private internal external pure view constant payable virtual override immutable anonymous indexed".split())
LOCATION = frozenset("storage memory calldata".split())
BINARY = [("||",), ("&&",), ("==", "!="), ("<", ">", "<=", ">="), ("|",), ("^",), ("&",), ("<<", ">>"), ("+", "-"), ("*", "/", "%"), ("**",)]
ASSIGN = frozenset("= += -= *= /= %= |= &= ^= <<= >>=".split())
#: Nesting beyond this is an error of the text, not of the stack.
MOST_DEPTH = 120


class SyntaxProblem(Exception):
    pass


@dataclass(eq=False)
class Node:
    kind: str
    line: int
    name: str = ""
    children: list = field(default_factory=list)
    roles: dict = field(default_factory=dict)
    props: dict = field(default_factory=dict)

    def add(self, role: str, child: Node | None) -> None:
        if child is not None:
            self.children.append(child)
            self.roles.setdefault(role, []).append(child)

    def get(self, role: str) -> Node | None:
        found = self.roles.get(role)
        return found[0] if found else None

    def all(self, role: str) -> list[Node]:
        return self.roles.get(role, [])

    def walk(self):
        stack = [self]
        while stack:
            n = stack.pop()
            yield n
            stack.extend(reversed(n.children))


def is_elementary(name: str) -> bool:
    return name in ELEMENTARY or any(name.startswith(p) and name[len(p) :].isdigit() for p in ("uint", "int", "bytes"))


class Parser:
    def __init__(self, code: str, lenient: bool = True) -> None:
        self.t: list[Token] = tokens(code, skip_placeholders=lenient)
        self.i, self.lenient, self.depth, self.problems = 0, lenient, 0, 0

    # -- tokens
    def peek(self, k: int = 0) -> str:
        j = self.i + k
        return self.t[j].text if j < len(self.t) else ""

    def kind(self, k: int = 0) -> str:
        j = self.i + k
        return self.t[j].kind if j < len(self.t) else "end"

    def line(self) -> int:
        return self.t[min(self.i, len(self.t) - 1)].line if self.t else 1

    def next(self) -> Token:
        if self.i >= len(self.t):
            raise SyntaxProblem("the text ends too early")
        self.i += 1
        return self.t[self.i - 1]

    def accept(self, text: str) -> bool:
        if self.i < len(self.t) and self.t[self.i].text == text and self.t[self.i].kind != "string":
            self.i += 1
            return True
        return False

    def expect(self, text: str) -> None:
        if not self.accept(text):
            if self.lenient and text in ")]}" and self.i >= len(self.t):
                return
            raise SyntaxProblem(f"line {self.line()}: {text} expected, {self.peek() or 'end'} found")

    def end_statement(self) -> None:
        if self.accept(";"):
            return
        if self.lenient and (self.i >= len(self.t) or self.peek() == "}" or self.t[self.i].fresh and self.peek() not in CONTINUES):
            return
        raise SyntaxProblem(f"line {self.line()}: statement does not end at {self.peek()}")

    def skip_balanced(self) -> None:
        """Over one statement or block that could not be read."""
        depth = 0
        while self.i < len(self.t):
            x = self.next().text
            if x in "([{":
                depth += 1
            elif x in ")]}":
                depth -= 1
                if depth <= 0 and x == "}":
                    return
                if depth < 0:
                    return
            elif x == ";" and depth == 0:
                return
            elif depth == 0 and self.i < len(self.t) and self.t[self.i].fresh:
                return

    # -- units and members
    def source(self) -> Node:
        root = Node("Source", 1)
        while self.i < len(self.t):
            at = self.i
            try:
                root.add("MEMBER", self.top())
            except SyntaxProblem:
                if not self.lenient:
                    raise
                self.problems += 1
                self.i = max(self.i, at + 1)
                self.skip_balanced()
        return root

    def top(self) -> Node | None:
        x = self.peek()
        if x in ("pragma", "import"):
            n = Node("Pragma", self.line(), x)
            words = []
            while self.i < len(self.t) and self.peek() != ";" and not (words and self.lenient and self.t[self.i].fresh):
                words.append(self.next().text)
            self.end_statement()
            n.props["text"] = "".join(words[2:]) if x == "pragma" else ""
            return n
        if x in ("contract", "interface", "library") and self.kind(1) == "name" or x == "abstract" and self.peek(1) == "contract":
            return self.record()
        if not self.lenient:
            raise SyntaxProblem(f"line {self.line()}: only declarations of units may stand here")
        member = self.member()
        return member if member is not None else self.statement()

    def record(self) -> Node:
        self.accept("abstract")
        n = Node("Record", self.line(), props={"kind": self.next().text})
        n.name = self.next().text
        if self.accept("is"):
            n.props["bases"] = []
            while self.peek() not in ("{", ""):
                n.props["bases"].append(self.next().text)
        self.expect("{")
        while self.i < len(self.t) and not self.accept("}"):
            at = self.i
            try:
                m = self.member()
                if m is None:
                    if not self.lenient:
                        raise SyntaxProblem(f"line {self.line()}: {self.peek()} is no member")
                    m = self.statement()
                n.add("FIELD" if m.kind == "Field" else "MEMBER", m)
            except SyntaxProblem:
                if not self.lenient:
                    raise
                self.problems += 1
                self.i = max(self.i, at + 1)
                self.skip_balanced()
        return n

    def member(self) -> Node | None:
        x, line = self.peek(), self.line()
        if x == "function" and (self.kind(1) == "name" or self.peek(1) == "(") or x in ("constructor", "fallback", "receive") and self.peek(1) == "(":
            return self.function()
        if x == "modifier" and self.kind(1) == "name":
            self.next()
            n = Node("Modifier", line, self.next().text)
            if self.peek() == "(":
                self.parameters(n)
            while self.peek() in ("virtual", "override"):
                self.next()
            n.add("BODY", self.block())
            return n
        if x in ("event", "error") and self.kind(1) == "name" and self.peek(2) == "(":
            self.next()
            n = Node("Event", line, self.next().text)
            self.parameters(n)
            self.accept("anonymous")
            self.end_statement()
            return n
        if x == "struct" and self.kind(1) == "name":
            self.next()
            n = Node("Struct", line, self.next().text)
            self.expect("{")
            while self.i < len(self.t) and not self.accept("}"):
                f = Node("StructField", self.line(), props={"type": self.type_name()})
                f.name = self.next().text
                self.end_statement()
                n.add("MEMBER", f)
            return n
        if x == "enum" and self.kind(1) == "name":
            self.next()
            n = Node("Enum", line, self.next().text)
            while self.i < len(self.t) and self.next().text != "}":
                pass
            return n
        if x == "using" and self.kind(1) == "name":
            n = Node("Using", line, self.peek(1))
            while self.i < len(self.t) and self.peek() != ";":
                self.next()
            self.end_statement()
            return n
        return self.field()

    def field(self) -> Node | None:
        """A state variable, if one stands here: a type, words of visibility or none, a name."""
        at = self.i
        try:
            kind = self.type_name()
            words = []
            while self.peek() in VISIBILITY:
                words.append(self.next().text)
            if self.kind() != "name" or not words and not (self.depth == 0 and at == self.i - 1 or self.peek(1) in ("=", ";", "")) or self.peek() in LOCATION:
                raise SyntaxProblem("no field")
            n = Node("Field", self.t[at].line, self.next().text, props={"type": kind, "words": words})
            if self.accept("="):
                n.add("INITIALIZER", self.expression())
            self.end_statement()
            return n
        except SyntaxProblem:
            self.i = at
            return None

    def parameters(self, n: Node, role: str = "PARAMETER") -> None:
        self.expect("(")
        while self.i < len(self.t) and not self.accept(")"):
            p = Node("Parameter", self.line(), props={"type": self.type_name()})
            while self.peek() in LOCATION or self.peek() in VISIBILITY:
                p.props["location"] = self.next().text
            if self.kind() == "name":
                p.name = self.next().text
            n.add(role, p)
            if not self.accept(",") and self.peek() != ")":
                raise SyntaxProblem(f"line {self.line()}: parameter list")

    def function(self) -> Node:
        n = Node("Function", self.line(), props={"words": [], "modifiers": []})
        word = self.next().text
        if word == "function":
            n.name = self.next().text if self.kind() == "name" else ""
        else:
            n.name = {"constructor": "constructor"}.get(word, "")
            n.props["words"].append(word)
        n.props["default"] = n.name == "" or n.name in ("fallback", "receive")
        self.parameters(n)
        while self.peek() not in ("{", ";", "") and not (self.lenient and self.peek() == "}"):
            x = self.next().text
            if x == "returns":
                self.parameters(n, "RETURNS")
            elif x in VISIBILITY:
                n.props["words"].append(x)
            else:
                args = []
                if self.accept("("):
                    args = self.arguments(")")
                n.props["modifiers"].append((x, args))
        if self.peek() == "{":
            n.add("BODY", self.block())
        else:
            self.end_statement()
        return n

    def type_name(self) -> str:
        t = self.next()
        if t.kind != "name":
            raise SyntaxProblem("no type")
        out = t.text
        if out == "mapping":
            self.expect("(")
            key = self.type_name()
            if self.kind() == "name":
                self.next()
            self.expect("=>")
            value = self.type_name()
            if self.kind() == "name":
                self.next()
            self.expect(")")
            out = f"mapping({key}=>{value})"
        elif out == "address" and self.accept("payable"):
            pass
        while self.peek() == "." and self.kind(1) == "name":
            self.next()
            out += "." + self.next().text
        while self.peek() == "[" and (self.peek(1) == "]" or self.peek(2) == "]"):
            self.next()
            size = "" if self.peek() == "]" else self.next().text
            self.expect("]")
            out += f"[{size}]"
        return out

    # -- statements
    def block(self) -> Node:
        n = Node("Block", self.line())
        self.expect("{")
        self.enter()
        while self.i < len(self.t) and not self.accept("}"):
            at = self.i
            try:
                n.add("STATEMENT", self.statement())
            except SyntaxProblem:
                if not self.lenient:
                    raise
                self.problems += 1
                self.i = max(self.i, at + 1)
                if self.t[self.i - 1].text != "}":
                    self.skip_balanced()
        self.depth -= 1
        return n

    def enter(self) -> None:
        self.depth += 1
        if self.depth > MOST_DEPTH:
            raise RecursionError("nested too deeply")

    def body(self) -> Node:
        return self.block() if self.peek() == "{" else self.statement()

    def statement(self) -> Node:
        x, line = self.peek(), self.line()
        if x == "{":
            return self.block()
        if x == ";":
            self.next()
            return Node("Empty", line)
        if x == "if":
            self.next()
            n = Node("If", line)
            self.expect("(")
            n.add("CONDITION", self.expression())
            self.expect(")")
            n.add("THEN", self.body())
            if self.accept("else"):
                n.add("ELSE", self.body())
            return n
        if x in ("while", "for"):
            self.next()
            n = Node("Loop", line, x)
            self.expect("(")
            if x == "for":
                n.add("INIT", None if self.accept(";") else self.statement())
                n.add("CONDITION", None if self.peek() == ";" else self.expression())
                self.expect(";")
                n.add("STEP", None if self.peek() == ")" else self.expression())
            else:
                n.add("CONDITION", self.expression())
            self.expect(")")
            n.add("BODY", self.body())
            return n
        if x == "do":
            self.next()
            n = Node("Loop", line, x)
            n.add("BODY", self.body())
            self.expect("while")
            self.expect("(")
            n.add("CONDITION", self.expression())
            self.expect(")")
            self.end_statement()
            return n
        if x in ("unchecked", "assembly") and self.peek(1) == "{" or x == "assembly" and self.kind(1) == "string":
            self.next()
            if self.kind() == "string":
                self.next()
            n = Node("SpecialBlock", line, x)
            if x == "assembly":
                depth = 0
                while self.i < len(self.t):
                    y = self.next().text
                    depth += (y == "{") - (y == "}")
                    if depth == 0:
                        break
            else:
                n.add("BODY", self.block())
            return n
        if x in ("return", "throw", "break", "continue") and self.kind() == "name":
            self.next()
            n = Node({"return": "Return", "throw": "Rollback"}.get(x, "Jump"), line, x)
            if x == "return" and self.peek() not in (";", "}", "") and not (self.lenient and self.t[self.i].fresh):
                n.add("VALUE", self.expression())
            self.end_statement()
            return n
        if x == "emit" and self.kind(1) == "name":
            self.next()
            n = Node("EmitEvent", line, self.peek())
            n.add("VALUE", self.expression())
            self.end_statement()
            return n
        if x == "_" and self.peek(1) in (";", "}", ""):
            self.next()
            self.end_statement()
            return Node("Placeholder", line)
        declared = self.declaration()
        if declared is not None:
            return declared
        n = Node("Expression", line)
        n.add("VALUE", self.expression())
        self.end_statement()
        return n

    def declaration(self) -> Node | None:
        at = self.i
        try:
            line = self.line()
            if self.peek() == "(" or self.peek() == "var" and self.peek(1) == "(":
                self.accept("var")
                self.next()
                n, any_ = Node("Declaration", line), self.t[self.i - 2].text == "var" if self.i > 1 else False
                while not self.accept(")"):
                    if self.accept(","):
                        continue
                    if any_:
                        kind = "var"
                    else:
                        kind = self.type_name()
                    where = self.next().text if self.peek() in LOCATION else ""
                    if self.kind() != "name":
                        raise SyntaxProblem("no declaration")
                    n.add("VARIABLE", Node("Variable", self.line(), self.next().text, props={"type": kind, "location": where}))
                self.expect("=")
                n.add("INITIALIZER", self.expression())
                self.end_statement()
                return n if n.all("VARIABLE") else self._back(at)
            kind = self.type_name()
            where = ""
            while self.peek() in LOCATION or self.peek() == "payable":
                where = self.next().text
            if self.kind() != "name" or self.t[self.i].fresh:
                return self._back(at)
            n = Node("Declaration", line)
            v = Node("Variable", line, self.next().text, props={"type": kind, "location": where})
            n.add("VARIABLE", v)
            if self.accept("="):
                n.add("INITIALIZER", self.expression())
            self.end_statement()
            return n
        except SyntaxProblem:
            return self._back(at)

    def _back(self, at: int) -> None:
        self.i = at

    # -- expressions
    def expression(self) -> Node:
        self.enter()
        left = self.ternary()
        if self.peek() in ASSIGN and self.kind() == "sign":
            n = Node("Assign", left.line, self.next().text)
            n.add("LHS", left)
            n.add("RHS", self.expression())
            left = n
        self.depth -= 1
        return left

    def ternary(self) -> Node:
        c = self.binary(0)
        if self.accept("?"):
            n = Node("Conditional", c.line, "?:")
            n.add("CONDITION", c)
            n.add("THEN", self.expression())
            self.expect(":")
            n.add("ELSE", self.expression())
            return n
        return c

    def binary(self, level: int) -> Node:
        if level == len(BINARY):
            return self.unary()
        left = self.binary(level + 1)
        while self.peek() in BINARY[level] and self.kind() == "sign":
            n = Node("BinaryOp", self.line(), self.next().text)
            n.add("LHS", left)
            n.add("RHS", self.binary(level + 1))
            left = n
        return left

    def unary(self) -> Node:
        if self.peek() in ("!", "-", "~", "++", "--", "+", "delete", "new") and self.kind() in ("sign", "name"):
            self.enter()
            n = Node("UnaryOp", self.line(), self.next().text)
            n.add("OPERAND", self.unary())
            self.depth -= 1
            return n
        return self.postfix()

    def arguments(self, close: str) -> list[Node]:
        out = []
        while self.i < len(self.t) and not self.accept(close):
            if self.accept(","):
                continue
            if self.peek() == "{":
                out += self.options()
                continue
            out.append(self.expression())
            if self.peek() not in (",", close):
                if self.lenient and self.i >= len(self.t):
                    break
                raise SyntaxProblem(f"line {self.line()}: argument list")
        return out

    def options(self) -> list[Node]:
        self.expect("{")
        out = []
        while not self.accept("}"):
            n = Node("CallOption", self.line(), self.next().text)
            self.expect(":")
            n.add("VALUE", self.expression())
            out.append(n)
            self.accept(",")
        return out

    def postfix(self) -> Node:
        n = self.primary()
        while self.i < len(self.t):
            x = self.peek()
            if self.t[self.i].fresh and x in ("(", "[", "++", "--", "{"):
                break
            if x == "." and self.kind(1) == "name":
                self.next()
                m = Node("Member", self.line(), self.next().text)
                m.add("BASE", n)
                n = m
            elif x == "(":
                call = Node("Call", self.line(), n.name)
                self.next()
                call.add("CALLEE", n)
                for a in self.arguments(")"):
                    call.add("OPTION" if a.kind == "CallOption" else "ARG", a)
                n = call
            elif x == "{" and self.kind(1) == "name" and self.peek(2) == ":" and n.kind in ("Member", "Reference"):
                opts = self.options()
                held = Node("Options", n.line, n.name)
                held.add("BASE", n)
                for o in opts:
                    held.add("OPTION", o)
                n = held
            elif x == "[":
                m = Node("Index", self.line(), "[]")
                self.next()
                m.add("BASE", n)
                m.add("INDEX", None if self.peek() == "]" else self.expression())
                self.expect("]")
                n = m
            elif x in ("++", "--"):
                m = Node("UnaryOp", self.line(), self.next().text)
                m.add("OPERAND", n)
                n = m
            else:
                break
        return n

    def primary(self) -> Node:
        if self.i >= len(self.t):
            raise SyntaxProblem("the text ends in an expression")
        t = self.t[self.i]
        if t.text == "(" and t.kind == "sign":
            self.next()
            items = self.arguments(")")
            if len(items) == 1:
                return items[0]
            n = Node("Tuple", t.line)
            for i in items:
                n.add("ARG", i)
            return n
        if t.text == "[" and t.kind == "sign":
            self.next()
            n = Node("Tuple", t.line, "[]")
            for i in self.arguments("]"):
                n.add("ARG", i)
            return n
        if t.kind in ("number", "string"):
            self.next()
            n = Node("Literal", t.line, t.text, props={"type": "number" if t.kind == "number" else "string"})
            if t.kind == "number" and self.peek() in ("wei", "gwei", "finney", "szabo", "ether", "seconds", "minutes", "hours", "days", "weeks", "years"):
                n.props["unit"] = self.next().text
            return n
        if t.kind == "name" and t.text not in ("else", "returns"):
            self.next()
            return Node("Reference", t.line, t.text)
        raise SyntaxProblem(f"line {t.line}: no expression at {t.text}")


def parse(code: str, mode: str = "lenient") -> Node:
    """The tree of a text; raises SyntaxProblem (strict) or RecursionError. ``props['problems']`` counts skipped places."""
    p = Parser(code, mode == "lenient")
    root = p.source()
    root.props["problems"] = p.problems
    return root


def parses(code: str, mode: str = "lenient") -> bool:
    """Whether a text is read without a skipped place and holds anything."""
    try:
        root = parse(code, mode)
    except (SyntaxProblem, RecursionError):
        return False
    return root.props["problems"] == 0 and bool(root.children)
