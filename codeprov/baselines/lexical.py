"""One expression for each rule and line, without a graph: a stand-in for scanners that look at text alone."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.graph.rules import BY_ID

PATTERNS = {
    "AC1": r"delegatecall\(|callcode\(",
    "AC2": r"selfdestruct\(|suicide\(",
    "AC3": r"tx\.origin",
    "AR1": r"=\s*\w+\s*[+*]\s*\w+|[+*]=",
    "AR2": r"=\s*\w+\s*-\s*\w+|-=",
    "BR1": r"block\.(difficulty|number|timestamp)|blockhash",
    "DS1": r"for\s*\(.*\.length",
    "DS2": r"\w+\.transfer\(",
    "FR2": r"\[msg\.sender\]\[\w+\]\s*=",
    "TM1": r"\bnow\b|block\.timestamp",
    "RE1": r"\.call\.value\(|\.call\{value",
    "SA1": r"function\s+\w+\(address\s+\w+,\s*uint",
    "UC1": r"^\s*\w+\.(call|send)\(",
}


def scan(units: DataFrame) -> DataFrame:
    """``unit_id, rule_id, category, line`` for every line that a rule's expression meets."""
    lines = units.select("unit_id", F.posexplode(F.split("code", "\n")).alias("i", "x"))
    hits = F.array_compact(F.array(*(F.when(F.col("x").rlike(p), F.struct(F.lit(k).alias("rule_id"), F.lit(BY_ID[k].category).alias("category"))) for k, p in PATTERNS.items())))
    return lines.select("unit_id", (F.col("i") + 1).cast("int").alias("line"), F.inline(hits)).select("unit_id", "rule_id", "category", "line")
