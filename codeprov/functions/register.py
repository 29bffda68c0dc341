"""Functions for SQL users; ``register(spark)`` adds them all to a session."""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf
from pyspark.sql.types import DoubleType, LongType, StringType, StructType

from codeprov.functions.pvalue import p_value
from codeprov.functions.text import levenshtein, order_free

_WORD = re.compile(r"[^\W_]+")


@F.udf(LongType(), useArrow=True)
def edit_distance(a, b):
    return None if a is None or b is None else levenshtein(a, b)


@F.udf(DoubleType(), useArrow=True)
def order_free_score(q, t):
    return None if not q or t is None else order_free(q, t)


@F.udf(DoubleType(), useArrow=True)
def part_delta(a, b):
    if a is None or b is None:
        return None
    longer = max(len(a), len(b))
    return 100.0 * (1 - levenshtein(a, b) / longer) if longer else 100.0


@F.udf(DoubleType(), useArrow=True)
def gram_containment(q, t):
    return None if not q or t is None else len(set(q) & set(t)) / len(set(q))


@pandas_udf(DoubleType())
def correlation(x: pd.Series, y: pd.Series) -> float:
    return float(x.corr(y))


@pandas_udf(DoubleType())
def t_pvalue(rho: pd.Series, n: pd.Series) -> pd.Series:
    return pd.Series([p_value(r, int(k)) if pd.notna(r) and pd.notna(k) else None for r, k in zip(rho, n, strict=True)])


@F.udtf(returnType=StructType().add("pos", LongType()).add("token", StringType()))
class TokenStream:
    """Runs of letters and digits of a text, lower-cased, with their places."""

    def eval(self, text: str):
        for i, m in enumerate(_WORD.finditer((text or "").lower())):
            yield i, m.group()


def register(spark: SparkSession) -> None:
    from codeprov.clone import fuzzyhash
    from codeprov.lang import frontend

    spark.udtf.register("fp_tokens", TokenStream)
    for name, f in (("edit_distance", edit_distance), ("order_free_score", order_free_score), ("part_delta", part_delta), ("gram_containment", gram_containment), ("t_pvalue", t_pvalue)):
        spark.udf.register(name, f)
    spark.udf.register("fp_hash", F.udf(lambda tokens: None if tokens is None else "".join(fuzzyhash.ctph(t.encode()) for t in tokens), "string"))
    spark.udf.register("fp_subs", F.udf(lambda fp: None if fp is None else [s for s in re.split("[.:]", fp) if s], "array<string>"))
    spark.udf.register("fp_grams", F.udf(lambda subs, n: None if subs is None else list(dict.fromkeys(s[i : i + n] for s in subs for i in range(len(s) - n + 1))), "array<string>"))
    spark.udf.register("strip_layout", F.udf(lambda code: None if code is None else frontend.strip_layout(code), "string"))
    spark.udf.register("canonical_code", F.udf(lambda code: None if code is None else frontend.canonical_text(code), "string"))
    spark.udf.register("is_parseable", F.udf(lambda code: code is not None and frontend.parseable(code), "boolean"))
    spark.udf.register("snippet_level", F.udf(lambda code: None if code is None else frontend.level_of(code), "string"))
    spark.udf.register("clone_type", F.udf(frontend.clone_type, "string"))
