"""A corpus pipeline: language, near duplicates, contamination, personal data, token ids.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame, which is written as Parquet and read again
as the next one's docs. All but the last return the columns of ``documents``. Extra columns are kept by
the first four. Each stage works on all that its predecessor kept; an empty table stays empty.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from codeprov.llm import bpe, decontaminate, langid, pii, simhash
from codeprov.llm.common import cut_lineage, held_out, table

#: Pre-tokens that a worker keeps, fewer than by default: the other stages' models and pages are still in memory.
KEPT = 250_000
COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a letter in any language (null texts too) go; the others stay as they are.

    Repeated rows stay repeated, very long texts are read whole, ties go to the language that sorts first.
    """
    samples = langid.fit(docs.where(~held_out(3, 1)).select("text", "lang"))
    marked = langid.predict(docs, samples, tuple(c for c in docs.columns if c != "text") + ("text",))
    return marked.where("lang_pred <> 'und'" if samples else "text RLIKE '\\\\p{L}'").select(*docs.columns)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies the document with the smallest id stays, once; rows without id stay."""
    found = simhash.near_duplicates(docs)
    first = found.where("doc_id = component_id").select("doc_id").distinct()
    order = [F.xxhash64("text").alias("_h"), "text"]
    kept = docs.join(first, "doc_id", "left_semi")
    once = kept.groupBy("doc_id").agg(F.count("*").alias("_n")).where("_n > 1").select("doc_id")
    repeated = kept.join(once, "doc_id", "left_semi")
    best = repeated.groupBy("doc_id").agg(F.min(F.struct(*order, *(c for c in docs.columns if c not in ("doc_id", "text")))).alias("_r"))
    best = best.select(*(F.col("doc_id") if c == "doc_id" else F.col(f"_r.{c}").alias(c) for c in docs.columns))
    return kept.join(once, "doc_id", "left_anti").select(*docs.columns).unionByName(best).unionByName(docs.where("doc_id is null"))


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents go of which a twentieth or more lies inside 13-word windows of benchmark items.

    Null and wordless texts hold none and stay, as does everything if there are no items; repeated rows are judged each.
    """
    found = decontaminate.contamination(docs, table(spark, sf_dir, "benchmark"), keep=docs.columns)
    return found.where("NOT contaminated").select(*docs.columns)


def personal_data_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every span of personal data is replaced by its kind; n_chars follows the text.

    A null text stays null (and its n_chars becomes null); rows are neither dropped nor merged.
    """
    out = pii.redact(docs)
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out


def token_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every text, with digests of the ids and of the bytes decoded from them; no token for a null text."""
    return bpe.encode(docs, keep=tuple(c for c in ("doc_id", "lang", "source") if c in docs.columns), kept=KEPT)


STAGES = [
    ("language_id", language_stage),
    ("simhash_dedup", near_duplicate_stage),
    ("decontaminate", decontamination_stage),
    ("pii", personal_data_stage),
    ("byte_bpe", token_stage),
]

#: SQL can express neither cross-parsing nor the segment model; tests hold the rows against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written to the shared folder and read again."""
    docs = table(spark, sf_dir, "documents")
    place = spark.conf.get("spark.checkpoint.dir", None)
    for name, stage in STAGES:
        out = stage(spark, docs, sf_dir)
        if place is None:
            docs = cut_lineage(out)
        else:
            path = f"{place.rstrip('/')}/pipeline-{uuid.uuid4().hex}/{name}"
            out.write.parquet(path)
            docs = spark.read.parquet(path)
    return docs
