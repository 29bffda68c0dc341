"""The reuse study: map snippets to units, check the snippets, keep later units, take code once, validate."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.clone import match
from codeprov.graph import local
from codeprov.session import cut_lineage
from codeprov.study import collect, temporal
from codeprov.study.source_profile import fingerprints


@dataclass(frozen=True)
class Config:
    setting: match.Setting = match.CONSERVATIVE
    budget: int | None = 20_000
    hop_schedule: tuple[int, ...] = (16, 8, 4, 2)


def map_clones(snippets: DataFrame, units: DataFrame, setting: match.Setting = match.CONSERVATIVE) -> DataFrame:
    """``snippet_id, unit_id, score``; both sides have code.

    Equal texts are parsed once and equal fingerprints compared once, on both sides; the pairs are those of all rows.
    """
    (q, asked), (t, held) = (_classes(d, id) for d, id in ((snippets, "snippet_id"), (units, "unit_id")))
    found = cut_lineage(match.find_clones(q, t, setting).select("query_id", "target_id", "score"))
    out = found.join(asked.withColumnRenamed("rep", "query_id"), "query_id").join(held.withColumnRenamed("rep", "target_id"), "target_id")
    return out.select("snippet_id", "unit_id", "score")


def _classes(df: DataFrame, id: str) -> tuple[DataFrame, DataFrame]:
    """Distinct fingerprints ``id, subs``, and ``rep`` with the id of each row that has it."""
    keyed = df.select(id, F.coalesce("code", F.lit("")).alias("code")).withColumn("_t", F.sha2("code", 256))
    texts = keyed.groupBy("_t").agg(F.min(id).alias("_i"), F.min_by("code", id).alias("code"))
    texts = cut_lineage(texts.repartition(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), "_t"))
    reps, members = match.collapse(fingerprints(texts, "_i"))
    names = texts.select("_t", "_i").join(members.withColumnRenamed("id", "_i"), "_i").select("_t", "rep")
    return reps, cut_lineage(keyed.select(id, "_t").join(names, "_t").select("rep", id))


def check_snippets(snippets: DataFrame) -> DataFrame:
    """``snippet_id, rules``: the rules that each weak snippet breaks."""
    found = local.evaluate_units(snippets, "snippet_id").where("rule_id IS NOT NULL")
    return found.groupBy(F.col("unit_id").alias("snippet_id")).agg(F.array_sort(F.collect_set("rule_id")).alias("rules"))


def by_text(units: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Distinct texts ``text_id, code`` (the id is the least of the units that have it), and the units with ``text_id`` in place of code."""
    keyed = units.withColumn("_t", F.coalesce(F.sha2("code", 256), F.lit("")))
    texts = keyed.groupBy("_t").agg(F.min("unit_id").alias("text_id"), F.first("code").alias("code"))
    return texts.select("text_id", "code"), keyed.drop("code").join(texts.select("_t", "text_id"), "_t").drop("_t")


def run(snippets: DataFrame, units: DataFrame, config: Config = Config(), texts: DataFrame | None = None) -> dict[str, DataFrame]:
    """All stages by name. snippets: snippet_id, code, posted_at; units: unit_id, code, deployed_at.

    With ``texts`` (text_id, code) units have text_id in place of code. The stages hold texts: what is found of a text holds
    of all units that have it, but for their times, so a stage is joined with ``units`` (also a stage) by ``later`` or
    ``reached`` where its units are asked for. Pairs of snippets and units are not written.
    """
    texts, units = by_text(units) if texts is None else (texts, units)
    texts, units = cut_lineage(texts.select("text_id", "code")), cut_lineage(units.select("unit_id", "text_id", "deployed_at"))
    span = units.groupBy("text_id").agg(F.min("deployed_at").alias("first_unit"), F.max("deployed_at").alias("last_unit"))
    as_units = texts.withColumnRenamed("text_id", "unit_id")
    matches = cut_lineage(map_clones(snippets, as_units, config.setting).withColumnRenamed("unit_id", "text_id"))
    flagged = cut_lineage(check_snippets(snippets))
    timed = matches.join(snippets.select("snippet_id", "posted_at"), "snippet_id").join(span, "text_id")
    candidates = cut_lineage(timed.join(flagged, "snippet_id"))
    classed = cut_lineage(temporal.with_class_of_texts(candidates))
    once, back = collect.dedup_units(as_units)
    coded = cut_lineage(classed.where("is_disseminator AND later").join(back.withColumnRenamed("unit_id", "text_id"), "text_id"))
    asked = coded.select("code_hash", F.explode("rules").alias("rule_id")).distinct().groupBy("code_hash").agg(F.collect_list("rule_id").alias("wanted"))
    work = cut_lineage(once.select("code_hash", "unit_id", "code").join(asked, "code_hash"))
    validated = cut_lineage(local.evaluate_units(work, rules="wanted", budget=config.budget, hop_schedule=config.hop_schedule).join(work.select("unit_id", "code_hash"), "unit_id"))
    kept = coded.select("snippet_id", "text_id", "posted_at", "code_hash", "is_source", F.explode("rules").alias("rule_id")).join(validated.where("rule_id IS NOT NULL").select("code_hash", "rule_id", "category").distinct(), ["code_hash", "rule_id"])
    return {"units": units, "matches": matches, "flagged": flagged, "classed": classed, "coded": coded, "validated": validated, "findings": cut_lineage(kept)}


def later(stage: DataFrame, units: DataFrame) -> DataFrame:
    """Rows of a stage with each unit that has their text and came after their snippet."""
    return stage.join(units, "text_id").where("deployed_at > posted_at")


def reached(stage: DataFrame, units: DataFrame, *by: str) -> DataFrame:
    """``unit_id`` (once) of ``later``, for each value of ``by``, without pairs: a unit is after any snippet if it is after the first."""
    first = stage.groupBy("text_id", *by).agg(F.min("posted_at").alias("posted_at"))
    return later(first, units).select("unit_id", *by).distinct()


def funnel(stages: dict[str, DataFrame], snippets: DataFrame) -> DataFrame:
    """``step, disseminator, source_only``: the counts along the way."""
    from functools import reduce

    c, k, f = stages["classed"], stages["coded"], stages["findings"]
    count = lambda d, col: (reached(d, stages["units"]) if col == "unit_id" else d).agg(F.count_distinct(col).alias("n"))
    rows = []
    for step, d, col in (
        ("weak snippets with clones", c, "snippet_id"),
        ("weak snippets with later clones", k, "snippet_id"),
        ("candidate units", k, "unit_id"),
        ("candidate codes", k, "code_hash"),
        ("validated snippets", f, "snippet_id"),
        ("validated units", f, "unit_id"),
        ("validated codes", f, "code_hash"),
    ):
        both = count(d, col).select(F.col("n").alias("disseminator")).join(count(d.where("is_source"), col).select(F.col("n").alias("source_only")))
        rows.append(both.select(F.lit(step).alias("step"), "disseminator", "source_only"))
    weak = snippets.join(stages["flagged"], "snippet_id", "left_semi").agg(F.count("*").alias("disseminator"))
    head = [snippets.agg(F.count("*").alias("disseminator")).select(F.lit("snippets").alias("step"), "disseminator", F.lit(None).cast("long").alias("source_only")), weak.select(F.lit("weak snippets").alias("step"), "disseminator", F.lit(None).cast("long").alias("source_only"))]
    return reduce(DataFrame.unionByName, head + rows)
