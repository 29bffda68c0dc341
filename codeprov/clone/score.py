"""Similarity of sub-fingerprints and of fingerprints, from 0 to 100."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

DIRECTIONS = ("forward", "backward", "max", "min", "mean")


def delta(a: Column | str, b: Column | str) -> Column:
    """100 for equal strings, 0 for strings without a common place: edit distance by the longer length."""
    a, b = (F.col(x) if isinstance(x, str) else x for x in (a, b))
    longer = F.greatest(F.length(a), F.length(b))
    return F.when(longer == 0, 100.0).otherwise(100.0 * (1 - F.levenshtein(a, b) / longer))


def _best(s: Column, target: Column) -> Column:
    # An equal part is the best there can be; no distance is taken then.
    return F.when(F.array_contains(target, s), 100.0).otherwise(F.coalesce(F.array_max(F.transform(target, lambda u: delta(s, u))), F.lit(0.0)))


def _forward(q: Column, t: Column, collapse_equal: bool) -> Column:
    scores = F.transform(q, lambda s: _best(s, t))
    if collapse_equal:
        scores = F.array_distinct(scores)
    return F.when(F.size(scores) > 0, F.aggregate(scores, F.lit(0.0), lambda x, y: x + y) / F.size(scores))


def order_free(q: Column | str, t: Column | str, direction: str = "forward", collapse_equal: bool = False) -> Column:
    """Mean, over the query's parts, of the best delta among the target's parts; null without query parts.

    It is not symmetric. ``collapse_equal`` keeps equal maxima once, as a literal set would.
    """
    q, t = (F.col(x) if isinstance(x, str) else x for x in (q, t))
    there, back = _forward(q, t, collapse_equal), _forward(t, q, collapse_equal)
    return {"forward": there, "backward": back, "max": F.greatest(there, back), "min": F.least(there, back), "mean": (there + back) / 2}[direction]


def part_floor(eps: float, parts: Column) -> Column:
    """The least best-delta that any single part may have if the mean of ``parts`` is to reach 100 eps."""
    return F.greatest(F.lit(0.0), 100 - parts * (100 - 100 * eps))


def order_free_bounded(q: Column | str, t: Column | str, eps: float) -> Column:
    """``order_free`` where it reaches 100 eps, else null; pairs whose lengths alone rule them out are not compared."""
    q, t = (F.col(x) if isinstance(x, str) else x for x in (q, t))
    floor = part_floor(eps, F.size(q))

    def best(s: Column) -> Column:
        def one(u: Column) -> Column:
            longer = F.greatest(F.length(s), F.length(u))
            most = F.floor((1 - floor / 100) * longer + 1e-9).cast("int")
            return F.when(F.abs(F.length(s) - F.length(u)) > most, -1.0).otherwise(100.0 * (1 - F.levenshtein(s, u) / longer))

        return F.coalesce(F.array_max(F.transform(t, one)), F.lit(-1.0))

    scores = F.transform(q, best)
    total = F.aggregate(scores, F.lit(0.0), lambda x, y: F.when((x < 0) | (y < 0), -1.0).otherwise(x + y))
    mean = F.when(F.size(q) > 0, total / F.size(q))
    return F.when(mean >= 100 * eps, mean)
