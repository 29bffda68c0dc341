"""Tokens of contract source, complete or not."""

from __future__ import annotations

import re
from dataclasses import dataclass

_TOKEN = re.compile(
    r"""(?P<comment>//[^\n]*|/\*(?s:.*?)(?:\*/|\Z))|(?P<string>hex"[^"\n]*"|"(?:[^"\\\n]|\\.)*"|'(?:[^'\\\n]|\\.)*')
    |(?P<number>0[xX][0-9a-fA-F]+|[0-9][0-9_]*(?:\.[0-9]+)?(?:[eE][0-9]+)?)|(?P<name>[A-Za-z_$][A-Za-z0-9_$]*)
    |(?P<dots>\.\.\.+|…)|(?P<newline>\n)|(?P<space>[ \t\r\f\v]+)
    |(?P<sign>>>>=|<<=|>>=|\*\*|=>|->|==|!=|<=|>=|&&|\|\||\+\+|--|\+=|-=|\*=|/=|%=|\|=|&=|\^=|<<|>>|.)""",
    re.VERBOSE,
)
#: A statement cannot end before these, so a newline there does not end it.
CONTINUES = frozenset(". , ) ] ? : = == != < > <= >= && || + - * / % ** += -= *= /= & | ^ ; {".split())


@dataclass(frozen=True)
class Token:
    kind: str
    text: str
    line: int
    #: A line break stands before this token.
    fresh: bool = False


def tokens(code: str, skip_placeholders: bool = True) -> list[Token]:
    """Names, numbers, strings and signs with their lines; comments go, and dots that stand for left-out code."""
    out, line, fresh = [], 1, False
    for m in _TOKEN.finditer(code):
        kind, text = m.lastgroup, m.group()
        if kind == "newline":
            line, fresh = line + 1, True
        elif kind == "comment":
            line += text.count("\n")
            fresh = fresh or "\n" in text
        elif kind == "dots":
            if not skip_placeholders:
                out.append(Token(kind, text, line, fresh))
            fresh = True
        elif kind != "space":
            out.append(Token(kind, text, line, fresh))
            line += text.count("\n")
            fresh = False
    return out
