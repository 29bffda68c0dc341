"""Fingerprints: letters of tokens, a dot between functions (sentences), a colon between units (lines)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from codeprov.clone.fuzzyhash import hash_tokens, part_letters

#: Boundaries of sentences and of words (fixed for the queries that SQL repeats).
PART, WORD = r"[.!?\n]+", r"[^\p{L}\p{N}]+"
#: Boundaries of units; each is a boundary of parts too.
UNIT = r"\n+"


def tokens(part: Column) -> Column:
    """Runs of letters and digits of a lower-cased text."""
    return F.filter(F.split(part, WORD), lambda t: t != "")


def parts(text: Column) -> Column:
    """Sentences of a text that hold a token, lower-cased."""
    return F.filter(F.split(F.lower(text), PART), lambda p: F.regexp_replace(p, WORD, "") != "")


def subs(text: Column | str, variant: str = "token64") -> Column:
    """Sub-fingerprints of a prose text, one for each sentence; empty for a null or wordless text."""
    c = F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit(""))
    if variant == "token64":
        return F.filter(F.transform(F.split(F.lower(c), PART), lambda p: hash_tokens(tokens(p))), lambda s: s != "")
    return part_letters(F.transform(parts(c), tokens), variant)


def build(df: DataFrame, id: str, text: str = "text", variant: str = "token64", units: bool = False) -> DataFrame:
    """``id, subs, n_subs, fp, len``: a narrow step over two columns.

    With ``units`` ``fp`` has colons between units in place of dots, and ``n_units`` counts those with a part.
    """
    out = df.select(F.col(id).alias("id"), subs(text, variant).alias("subs"), *([_unit_sizes(text).alias("_sizes")] if units else []))
    if units:
        out = out.withColumns({"fp": F.array_join(_units("subs", "_sizes"), ":"), "n_units": F.size("_sizes")}).drop("_sizes")
    else:
        out = out.withColumn("fp", F.array_join("subs", "."))
    return out.withColumns({"n_subs": F.size("subs"), "len": F.length("fp")})


def _unit_sizes(text: Column | str) -> Column:
    """Numbers of parts of the units that have one."""
    c = F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit(""))
    return F.filter(F.transform(F.split(c, UNIT), lambda u: F.size(parts(u))), lambda n: n > 0)


def _units(subs: Column | str, sizes: Column | str) -> Column:
    """Parts of each unit, joined by dots, from the parts of all and the units' sizes."""
    before = lambda i: F.aggregate(F.slice(sizes, F.lit(1), i), F.lit(0), lambda x, y: x + y)
    return F.transform(sizes, lambda n, i: F.array_join(F.slice(subs, before(i) + 1, n), "."))


def split_subs(fp: Column | str) -> Column:
    """Sub-fingerprints of a joined fingerprint with dots and colons."""
    return F.filter(F.split(fp, "[.:]"), lambda s: s != "")


def dictionary(prints: DataFrame) -> DataFrame:
    """Distinct sub-fingerprints with the number of fingerprints that hold each: clones collapse here."""
    return prints.select("id", F.explode(F.array_distinct("subs")).alias("s")).groupBy("s").agg(F.count("*").alias("df"))


def store(prints: DataFrame, name: str, buckets: int = 64) -> None:
    """Fingerprints as a table bucketed by id, so that later joins on the id need no shuffle."""
    prints.write.mode("overwrite").bucketBy(buckets, "id").sortBy("id").saveAsTable(name)
