"""Distinct N-grams of fingerprints."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def grams(subs: Column | str, n: int = 3, cross_separators: bool = False) -> Column:
    """Distinct substrings of length ``n`` of each sub-fingerprint; with ``cross_separators`` of the joined one.

    Parts shorter than ``n`` give none (Spark's sequence would count down, hence the guard).
    """
    c = F.col(subs) if isinstance(subs, str) else subs
    if cross_separators:
        c = F.array(F.array_join(c, "."))
    one = lambda s: F.transform(F.sequence(F.lit(1), F.length(s) - n + 1), lambda i: F.substr(s, i, F.lit(n)))
    return F.array_distinct(F.flatten(F.transform(F.filter(c, lambda s: F.length(s) >= n), one)))
