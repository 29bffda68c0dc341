"""Layout and identifier normalisation before tokens are cut (prose here; the source profile is in ``lang``)."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: One alternative for each thing that layout stripping must keep or drop: strings are kept whole, comments go.
_LITERAL_OR_COMMENT = r'("(?:[^"\\\n]|\\.)*"|\'(?:[^\'\\\n]|\\.)*\')|//[^\n]*|/\*(?s:.*?)\*/'


def strip_comments(col: Column | str) -> Column:
    """Source text without comments; quoted text is left alone."""
    return F.regexp_replace(col, _LITERAL_OR_COMMENT, "$1")


def strip_layout(col: Column | str, profile: str = "prose") -> Column:
    """Text whose layout no longer matters: case and runs of white space (prose), comments and all blanks (source)."""
    c = F.col(col) if isinstance(col, str) else col
    if profile == "source":
        return F.regexp_replace(strip_comments(c), r"\s+", "")
    return F.trim(F.regexp_replace(F.lower(c), r"\s+", " "))


def mask_prose(col: Column | str, literals: str = "mask", numbers: str = "keep", names: str = "mask") -> Column:
    """Quoted spans to one word, addresses and phone numbers to type words, and (as an ablation) numbers to one word."""
    c = F.col(col) if isinstance(col, str) else col
    if literals == "mask":
        c = F.regexp_replace(c, r'"[^"\n]*"', " stringLiteral ")
    if names == "mask":
        c = F.regexp_replace(c, r"[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+", " emailName ")
        c = F.regexp_replace(c, r"\+[0-9][0-9() .-]{6,}[0-9]", " phoneName ")
    if numbers == "mask":
        c = F.regexp_replace(c, r"[0-9]+", "0")
    return c
