"""From posts to distinct snippets in the wanted language."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from codeprov.clone.normalise import strip_comments

#: Frequent words of four languages (our own short lists; the languages' words are public knowledge).
KEYWORDS = {
    "en": "the of and to in is that it for as with was on be by not are this".split(),
    "de": "der die und das in den von zu mit ist nicht ein auf im als so es".split(),
    "fr": "le la de et les des en un une que qui dans pour est du au pas sur".split(),
    "es": "el la de que y en los las un por con no una para es se del su".split(),
}


def posts(df: DataFrame, tag: str | None, until, tag_column: str = "tag", at: str = "created_at") -> DataFrame:
    """Posts with a tag up to a time; both filters reach the scan."""
    out = df if tag is None else df.where(F.col(tag_column) == tag)
    return out.where(F.col(at) <= until)


def extract_snippets(df: DataFrame, body: str = "body", tags: tuple[str, ...] = ("code", "pre")) -> DataFrame:
    """One row for each block of the tags, with its place and its text without markup; posts without one are kept by a null."""
    inner = rf"(?s)<(?:{'|'.join(tags)})\b[^>]*>(.*?)</(?:{'|'.join(tags)})>"
    blocks = F.regexp_extract_all(body, F.lit(inner), F.lit(1))
    out = df.select("*", F.posexplode_outer(blocks).alias("position", "raw"))
    return out.withColumn("text", plain(F.col("raw"))).drop("raw")


def plain(markup: Column) -> Column:
    """Text of a markup fragment: tags dropped, the five common entities decoded, trimmed."""
    c = F.regexp_replace(markup, "<[^>]*>", "")
    for entity, sign in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")):
        c = F.replace(c, F.lit(entity), F.lit(sign))
    return F.trim(c)


def exclusive(language: str, keywords: dict[str, list[str]] | None = None) -> list[str]:
    """Words of a language that no other list has."""
    words = keywords or KEYWORDS
    return sorted(set(words[language]) - {w for k, v in words.items() if k != language for w in v})


def words(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), lambda w: w != "")


def keyword_hits(text: Column, keywords: list[str]) -> Column:
    """Number of distinct keywords in a text."""
    return F.size(F.array_intersect(words(text), F.array(*map(F.lit, keywords))))


def keyword_filter(df: DataFrame, keywords: list[str], other: list[str] = (), min_hits: int = 1, text: str = "text") -> DataFrame:
    own = sorted(set(keywords) - set(other))
    return df.where(keyword_hits(F.col(text), own) >= min_hits)


def dedup(df: DataFrame, scope: str = "global", text: str = "text", at: str = "posted_at", source: str = "site") -> DataFrame:
    """Equal texts once, the earliest post kept; ``scope`` per_source or global. By aggregation, so a hot text is no skew."""
    keys = ([source] if scope == "per_source" else []) + ["_h"]
    rest = [c for c in df.columns if c not in keys]
    best = df.withColumn("_h", F.sha2(text, 256)).groupBy(*keys).agg(F.min_by(F.struct(*rest), F.col(at)).alias("_r"))
    return best.select(*([source] if scope == "per_source" else []), "_r.*").select(*df.columns)


def dedup_units(df: DataFrame, code: str = "code", id: str = "unit_id") -> tuple[DataFrame, DataFrame]:
    """Units with comment-free code taken once, and ``code_hash, unit_id`` for giving results back."""
    hashed = df.withColumn("code_hash", F.sha2(F.regexp_replace(strip_comments(code), r"\s+", " "), 256))
    once = hashed.groupBy("code_hash").agg(F.min_by(F.struct(*df.columns), F.col(id)).alias("_r")).select("code_hash", "_r.*")
    return once, hashed.select("code_hash", id)


def first_of(df: DataFrame, keys: list[str], order: list[str]) -> DataFrame:
    """Marks the first row of each group."""
    return df.withColumn("first", F.row_number().over(Window.partitionBy(*keys).orderBy(*order)) == 1)
