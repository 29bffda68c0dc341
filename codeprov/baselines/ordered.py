"""Edit distance over whole fingerprints: the order of parts counts."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType

from codeprov.clone.score import delta
from codeprov.functions.text import levenshtein_bits

#: Letters of both strings from which the distance is taken with one bit a letter.
LONG = 100


@F.udf(IntegerType(), useArrow=True)
def _long_distance(a, b):
    return None if a is None or b is None else levenshtein_bits(a, b)


def whole_score(a: Column | str, b: Column | str) -> Column:
    """``delta`` of two strings of any length."""
    a, b = (F.col(x) if isinstance(x, str) else x for x in (a, b))
    long = (F.length(a) >= LONG) & (F.length(b) >= LONG)
    far = _long_distance(F.when(long, a), F.when(long, b))
    return F.when(long, 100.0 * (1 - far / F.greatest(F.length(a), F.length(b)))).otherwise(delta(a, b))
