"""What a physical plan holds, for tests and for reviewing a query before it meets 100 TB."""

from __future__ import annotations

import re
from collections import Counter
from dataclasses import dataclass

from pyspark.sql import DataFrame

_NODE = re.compile(r"^[\s:+\-|*()0-9]*([A-Z]\w+)")


@dataclass(frozen=True)
class Plan:
    nodes: Counter
    pushed: tuple[str, ...]
    columns: tuple[str, ...]
    single_partition: bool

    def has(self, *names: str) -> bool:
        return any(self.nodes[n] for n in names)


def inspect(df: DataFrame) -> Plan:
    """Operators with their number, filters pushed to scans, columns read, and whether all rows meet in one task."""
    text = df._jdf.queryExecution().executedPlan().toString()
    nodes = Counter(m[1] for line in text.splitlines() if (m := _NODE.match(line)))
    # Only the formatted text shows long filters and schemas in full.
    full = df.sparkSession.sparkContext._jvm.PythonSQLUtils.explainString(df._jdf.queryExecution(), "formatted")
    pushed = tuple(x for x in re.findall(r"PushedFilters: \[(.*)\]", full) if x)
    columns = tuple(re.findall(r"ReadSchema: struct<(.*)>", full))
    windows = re.findall(r"Window .*", text)
    return Plan(nodes, pushed, columns, bool(windows) and "SinglePartition, ENSURE" in text)
