"""Small programs of our own, one weak and one mitigated for each rule, for consistency checks.

``head`` are declarations, ``one`` the function of interest, ``two`` another one. WEAK marks the line that
a finding must name; /*+*/ where a harmless statement may be put in; /*-*/ ends a harmless line that may go.
A capital A, B or C that ends a name is replaced by a word of the row.
"""

from __future__ import annotations

import re
from dataclasses import dataclass


@dataclass(frozen=True)
class Template:
    rule_id: str
    category: str
    weak: bool
    head: str
    one: str
    two: str
    version: str = "0.4.24"


_LOG = "function noteA(bytes32 what) public {\n  emit Seen(what); /*-*/\n  emit Seen(what);\n}"
_PAIRS = [
    ("AC1", "access control", "address targetA;", "function() payable {\n  bool done = targetA.delegatecall(msg.data); /*WEAK*/\n  require(done);\n}", "function() payable {\n  require(msg.sig == 0x12345678);\n  bool done = targetA.delegatecall(msg.data);\n  require(done);\n}"),
    ("AC2", "access control", "address ownerA;\nconstructor() public { ownerA = msg.sender; }", "function closeB() public {\n  emit Seen(0x01); /*+*/\n  selfdestruct(msg.sender); /*WEAK*/\n}", "function closeB() public {\n  require(msg.sender == ownerA);\n  selfdestruct(msg.sender);\n}"),
    ("AC3", "access control", "address keeperA;\nuint levelB;", "function setB(uint next) public {\n  require(tx.origin == keeperA); /*WEAK*/\n  levelB = next;\n}", "function setB(uint next) public {\n  require(tx.origin == msg.sender);\n  levelB = next;\n}"),
    ("AC4", "access control", "address chiefA;\nuint levelB;\nfunction raiseC() public {\n  require(msg.sender == chiefA);\n  levelB = 5;\n}", "function claimA() public {\n  emit Seen(0x02); /*+*/\n  chiefA = msg.sender; /*WEAK*/\n}", "function claimA(address next) public {\n  require(msg.sender == chiefA);\n  chiefA = next;\n}"),
    ("AR1", "arithmetic", "uint totalA;", "function growA(uint much) public {\n  emit Seen(0x03); /*+*/\n  totalA = totalA + much; /*WEAK*/\n}", "function growA(uint much) public {\n  uint sum = totalA + much;\n  require(sum >= totalA);\n  totalA = sum;\n}"),
    ("AR2", "arithmetic", "uint stockA;", "function sinkA(uint much) public {\n  emit Seen(0x04); /*+*/\n  stockA -= much; /*WEAK*/\n}", "function sinkA(uint much) public {\n  require(stockA >= much);\n  stockA -= much;\n}"),
    ("BR1", "bad randomness", "uint prizeA;", "function drawA() public payable {\n  uint spin = uint(block.difficulty) % 10; /*WEAK*/\n  if (spin == 7) {\n    msg.sender.transfer(prizeA);\n  }\n}", "function drawA() public payable {\n  uint until = block.number;\n  if (until == 7) {\n    msg.sender.transfer(prizeA);\n  }\n}"),
    ("DS1", "denial of service", "address[] listA;\nmapping(address => uint) dueB;\nfunction joinC() public { listA.push(msg.sender); }", "function resetA() public {\n  for (uint i = 0; i < listA.length; i++) { /*WEAK*/\n    dueB[listA[i]] = 0;\n  }\n}", "function resetA() public {\n  for (uint i = 0; i < 20; i++) {\n    dueB[listA[i]] = 0;\n  }\n}"),
    ("DS2", "denial of service", "address leaderA;\nuint priceB;", "function leadA() public payable {\n  emit Seen(0x05); /*+*/\n  leaderA.transfer(priceB); /*WEAK*/\n  leaderA = msg.sender;\n}", "function leadA() public payable {\n  msg.sender.transfer(priceB);\n  leaderA = msg.sender;\n}"),
    ("FR1", "front running", "bytes32 answerA;\nuint prizeB;", "function solveA(bytes32 guess) public {\n  require(guess == answerA);\n  emit Seen(guess); /*+*/\n  msg.sender.transfer(prizeB); /*WEAK*/\n}", "mapping(address => bytes32) heldC;\nfunction solveA(bytes32 guess) public {\n  require(guess == heldC[msg.sender]);\n  msg.sender.transfer(prizeB);\n}"),
    ("FR2", "front running", "mapping(address => mapping(address => uint)) allowA;", "function permitA(address who, bytes32 tag, uint much) public {\n  emit Seen(tag); /*+*/\n  allowA[msg.sender][who] = much; /*WEAK*/\n}", "function permitA(address who, bytes32 tag, uint much) public {\n  require(much == 0);\n  allowA[msg.sender][who] = much;\n}"),
    ("TM1", "time manipulation", "uint openA;\nuint roundB;", "function tickA() public {\n  if (now > openA) { /*WEAK*/\n    roundB = 2;\n  }\n}", "function tickA() public {\n  if (now > openA + 2 days) {\n    roundB = 2;\n  }\n}"),
    ("RE1", "reentrancy", "mapping(address => uint) heldA;", "function takeA() public {\n  uint much = heldA[msg.sender];\n  bool done = msg.sender.call.value(much)(); /*WEAK*/\n  require(done);\n  heldA[msg.sender] = 0;\n}", "bool busyC;\nfunction takeA() public {\n  require(!busyC);\n  busyC = true;\n  uint much = heldA[msg.sender];\n  bool done = msg.sender.call.value(much)();\n  require(done);\n  heldA[msg.sender] = 0;\n}"),
    ("RE2", "reentrancy", "bool paidA;\nuint feeB;\nfunction stateC() public view returns (bool) { return paidA; }", "function payA() public {\n  emit Seen(0x06); /*+*/\n  bool done = msg.sender.call.value(feeB)(); /*WEAK*/\n  require(done);\n  paidA = true;\n}", "function payA() public {\n  bool done = msg.sender.call.value(feeB).gas(2300)();\n  require(done);\n  paidA = true;\n}"),
    ("SA1", "short addresses", "mapping(address => uint) creditA;", "function giveA(address who, uint much) public { /*WEAK*/\n  emit Seen(0x07); /*+*/\n  creditA[who] = much;\n}", "function giveA(address who, uint much) public {\n  require(msg.data.length >= 68);\n  creditA[who] = much;\n}"),
    ("UC1", "unchecked low level calls", "address otherA;", "function pokeA() public {\n  emit Seen(0x08); /*+*/\n  otherA.call(0x11223344); /*WEAK*/\n}", "function pokeA() public {\n  bool done = otherA.call(0x11223344);\n  require(done);\n}"),
    ("UU1", "unknown unknowns", "struct Entry { uint amount; }\nEntry[] rowsA;", "function markA() public {\n  Entry storage row;\n  row.amount = 4; /*WEAK*/\n}", "function markA() public {\n  Entry storage row = rowsA[0];\n  row.amount = 4;\n}"),
]
TEMPLATES: tuple[Template, ...] = tuple(Template(rule, category, weak, f"event Seen(bytes32 what);\n{head}", one, _LOG) for rule, category, head, bad, good in _PAIRS for weak, one in ((True, bad), (False, good)))
MUTATIONS = ("none", "layout", "renamed", "inserted", "removed", "reordered")
#: Words of each level of cutting: the whole unit, its functions, the labelled statement and its neighbours.
LEVELS = ("unit", "function", "statement")


def render(template: int, mutation: int = 0, a: str = "Alpha", b: str = "Beta", c: str = "Gamma", unit: str = "Depot") -> str:
    """The program of a template; the mutation keeps its weakness (or its mitigation) as it is."""
    t = TEMPLATES[template]
    parts = [t.one, t.two] if mutation != 5 else [t.two, t.one]
    if mutation == 3:
        parts = [p.replace("/*+*/", "emit Seen(0xff);") for p in parts]
    if mutation == 4:
        parts = ["\n".join(x for x in p.split("\n") if not x.endswith("/*-*/")) for p in parts]
    body = "\n".join([t.head, *parts])
    names = (a, b, c) if mutation != 2 else (c + "X", a + "Y", b + "Z")
    for key, name in zip("ABC", names, strict=True):
        body = _renamed(body, key, name)
    text = f"pragma solidity ^{t.version};\ncontract {unit} {{\n{body}\n}}\n"
    if mutation == 1:
        text = text.replace("\n  ", "\n      ").replace(";\n", "; // kept\n")
    return text


def _renamed(body: str, key: str, name: str) -> str:
    """A capital that ends a name of ours becomes the row's word."""
    return re.sub(rf"(?<=[a-z]){key}(?![A-Za-z])", name, body)


def weak_line(code: str) -> int:
    """Line of the mark, from 1; 0 without one."""
    return next((i for i, x in enumerate(code.split("\n"), 1) if "/*WEAK*/" in x), 0)


def fragment(code: str, template: int, level: str, around: int = 5) -> tuple[str, int]:
    """The text cut to a level, and the mark's line in it (0 without a mark).

    function: the function of interest alone; statement: the lines from the mark, or the middle, with up to
    ``around`` lines on each side, without the function's first and last line.
    """
    if level == "unit":
        return code, weak_line(code)
    lines = code.split("\n")
    stem = re.findall(r"^function ?([a-z]*)", TEMPLATES[template].one, re.MULTILINE)[-1]
    start = next(i for i, x in enumerate(lines) if re.match(rf"\s*function ?{stem}[A-Z]?\w*\(", x) and (stem or re.match(r"\s*function ?\(", x)))
    depth, end = 0, start
    for i in range(start, len(lines)):
        depth += lines[i].count("{") - lines[i].count("}")
        if depth == 0 and "}" in lines[i]:
            end = i
            break
    if level == "function":
        text = "\n".join(lines[start : end + 1])
        return text, weak_line(text)
    inner = lines[start + 1 : end]
    at = next((i for i, x in enumerate(inner) if "/*WEAK*/" in x), len(inner) // 2)
    text = "\n".join(inner[max(0, at - around) : at + around + 1])
    return text, weak_line(text)
