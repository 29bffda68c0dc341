"""Fingerprints of source code: canonical tokens of each function, one letter a token."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.clone.fuzzyhash import hash_tokens, part_letters
from codeprov.lang import frontend, parse


def canonical(df: DataFrame, id: str, code: str = "code", **options) -> DataFrame:
    """``id, parts``: arrays of canonical tokens; unreadable texts have none. Options: names, literals, numbers, drop_visibility."""

    def work(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            rows = []
            for i, text in zip(b["id"], b["code"], strict=True):
                try:
                    rows.append((i, frontend.canonical_parts(text or "", **options)))
                except (parse.SyntaxProblem, RecursionError):
                    rows.append((i, []))
            yield pd.DataFrame(rows, columns=["id", "parts"])

    return df.selectExpr(f"`{id}` AS id", f"`{code}` AS code").mapInPandas(work, "id long, parts array<array<string>>")


def fingerprints(df: DataFrame, id: str, code: str = "code", variant: str = "token64", **options) -> DataFrame:
    """``id, subs`` as the clone finder takes them."""
    parts = canonical(df, id, code, **options)
    if variant == "token64":
        return parts.select("id", F.filter(F.transform("parts", lambda p: hash_tokens(p)), lambda s: s != "").alias("subs"))
    return parts.select("id", part_letters("parts", variant).alias("subs"))
