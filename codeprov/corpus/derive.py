"""Units and snippets rendered from the given tables: a pure function of their rows, nothing is stored."""

from __future__ import annotations

import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.corpus import templates as T

_UNIT = "unit_id long, template int, family int, weak boolean, rule_id string, category string, line int, mutation int, code string"


def _words(text: str | None) -> list[str]:
    found = [w.capitalize() for w in re.findall("[A-Za-z]{2,}", text or "")]
    return (found + ["Alpha", "Beta", "Gamma"])[:3]


def programs(rows: DataFrame, level: str = "unit") -> DataFrame:
    """``rows`` has id, template, mutation, name: the program of each, cut to a level, with its label (line 0: none).

    A column ``n`` is kept.
    """
    kept = [c for c in ("n",) if c in rows.columns]

    def work(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            out = []
            for r in b.itertuples(index=False):
                t = T.TEMPLATES[r.template]
                code, line = T.fragment(T.render(int(r.template), int(r.mutation), *_words(r.name)), int(r.template), level)
                out.append((r.id, r.template, r.template // 2, t.weak, t.rule_id, t.category, line, r.mutation, code, *(getattr(r, c) for c in kept)))
            yield pd.DataFrame(out, columns=["unit_id", "template", "family", "weak", "rule_id", "category", "line", "mutation", "code", *kept])

    return rows.select("id", "template", "mutation", "name", *kept).mapInPandas(work, _UNIT + "".join(f", {c} long" for c in kept))


def unit_rows(part: DataFrame) -> DataFrame:
    n = len(T.TEMPLATES)
    return part.select(F.col("p_partkey").alias("id"), (F.col("p_partkey") % n).cast("int").alias("template"), (F.coalesce("p_size", F.lit(0)) % 6).cast("int").alias("mutation"), F.col("p_name").alias("name"))


def units(part: DataFrame, level: str = "unit") -> DataFrame:
    n = int(part.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return programs(unit_rows(part).repartition(n, "template", "mutation", "name"), level)


def kinds(part: DataFrame, level: str = "unit") -> DataFrame:
    """Distinct programs of all parts: ``unit_id`` is the least of the units that have each, ``n`` their number.

    A program is a function of template, mutation and name, so what holds of one of them holds of all ``n``.
    """
    rows = unit_rows(part).groupBy("template", "mutation", "name").agg(F.min("id").alias("id"), F.count("*").alias("n"))
    return programs(rows.repartition(int(part.sparkSession.conf.get("spark.sql.shuffle.partitions")), "id"), level)


def shared(rows: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Distinct programs of ``rows`` (those of ``unit_rows``, with any further columns), and the rows with ``text_id`` in place of what makes a program.

    ``text_id`` is the least id of the rows that have a program, and its ``unit_id``. Nothing is rendered twice.
    """
    keys = ("template", "mutation", "name")
    least = rows.groupBy(*keys).agg(F.min("id").alias("text_id"))
    names = least.select("text_id", *(F.col(k).alias(f"_{k}") for k in keys))
    members = rows.join(names, F.expr(" AND ".join(f"{k} <=> _{k}" for k in keys))).drop(*keys, *(f"_{k}" for k in keys))
    n = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return programs(least.withColumnRenamed("text_id", "id").repartition(n, "id")), members.withColumnRenamed("id", "unit_id")


def snippets(benchmark: DataFrame, level: str = "function") -> DataFrame:
    n = len(T.TEMPLATES)
    rows = benchmark.select(F.col("item_id").alias("id"), (F.col("item_id") % n).cast("int").alias("template"), F.lit(0).alias("mutation"), F.col("text").alias("name"))
    return programs(rows, level)
