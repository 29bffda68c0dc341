"""Workloads over derived programs: rule checking, clone classes, the reuse study, review."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.baselines import lexical, published
from codeprov.clone import match
from codeprov.corpus import derive
from codeprov.corpus import templates as T
from codeprov.graph import local
from codeprov.lang import frontend
from codeprov.measure import confusion, funnel
from codeprov.session import cut_lineage, table
from codeprov.study import pipeline, review
from codeprov.study.source_profile import fingerprints


def _units(spark, sf, level="unit"):
    return derive.units(table(spark, sf, "part"), level)


def _truth(units: DataFrame) -> DataFrame:
    return units.where("weak AND line > 0").select("unit_id", "rule_id", "category", "line")


def w08(spark, sf):
    """Clone classes: units of one family are clones of each other; the finder against the families, all pairs.

    Equal programs, and then equal fingerprints, are searched once and count for all their units.
    """
    units = cut_lineage(derive.kinds(table(spark, sf, "part")))
    reps, members = match.collapse(fingerprints(units, "unit_id"))
    kinds = units.select(F.col("unit_id").alias("id"), F.col("rule_id").alias("class"), "n")
    classes = members.join(kinds, "id").groupBy(F.col("rep").alias("id"), "class").agg(F.sum("n").alias("n"))
    return confusion.class_pairs(match.class_clones(reps), cut_lineage(classes)).select("class", "tp", "fp", F.col("labels").alias("same_pairs"), F.col("rec").alias("recall"))


def w24(spark, sf):
    return local.evaluate_units(_units(spark, sf)).where("rule_id IS NOT NULL").select("unit_id", "rule_id", "category", F.col("line").cast("long").alias("line"))


def w25(spark, sf):
    """Labels, hits and wrong findings of each tool; every distinct program is checked once and counts for all its units."""
    units = cut_lineage(derive.kinds(table(spark, sf, "part")))
    truth = _truth(units).join(units.select("unit_id", "n"), "unit_id")
    sets = units.select("unit_id", "category", "n")
    tools = {
        "full": local.evaluate_units(units),
        "no mitigations": local.evaluate_units(units, use_mitigations=False),
        "no relevancy": local.evaluate_units(units, use_relevancy=False),
        "no wrappers": local.evaluate_units(units, infer=False),
        "no copies": local.evaluate_units(units, expand=False),
        "no extra flow": local.evaluate_units(units, indirect_flow=False),
        "no wrappers, copies or extra flow": local.evaluate_units(units, infer=False, expand=False, indirect_flow=False),
        "lexical": lexical.scan(units),
    }
    out = []
    for name, found in tools.items():
        found = cut_lineage(found.where("rule_id IS NOT NULL").select("unit_id", "rule_id", "category", "line"))
        # Wrong findings count within the test set of their category, which holds mitigated programs too.
        wrong = confusion.fp(found, truth, False).join(sets, ["unit_id", "category"])
        one = lambda d, n: d.groupBy("category").agg(F.sum("n").alias(n))
        rows = one(truth, "labels").join(one(confusion.tp(found, truth), "tp"), "category", "left").join(one(wrong, "fp"), "category", "left").na.fill(0)
        total = rows.agg(*(F.sum(c).alias(c) for c in ("labels", "tp", "fp"))).withColumn("category", F.lit("total"))
        out.append(rows.unionByName(total).select(F.lit(name).alias("tool"), "category", "labels", "tp", "fp"))
    return reduce(DataFrame.unionByName, out)


def _reports(spark, sf) -> tuple[DataFrame, DataFrame]:
    """Findings of a scripted tool with the cause of each, and the labels: it errs by the unit's number.

    A label of every fifth unit is reported a line too far, of every seventh unit twice, of every eleventh unit
    not at all; every third program without a weakness is reported for the one that it mitigates.
    """
    units = cut_lineage(_units(spark, sf).select("unit_id", "rule_id", "category", "weak", "line"))
    n = F.col("unit_id")
    weak, safe = F.expr("weak AND line > 0"), F.expr("NOT weak AND unit_id % 3 = 0")
    reports = units.where((weak & (n % 11 != 0)) | safe)
    reports = reports.withColumn("cause", F.when(safe, "mitigated").when(n % 5 == 0, "other line").when(n % 7 == 0, "repeated"))
    line = F.when(F.col("cause") == "other line", F.col("line") + 1).when(F.col("cause") == "mitigated", 1).otherwise(F.col("line"))
    times = F.array_repeat(F.lit(0), F.when(n % 7 == 0, 2).otherwise(1))
    return reports.select("unit_id", "rule_id", "category", line.alias("line"), "cause", F.explode(times).alias("_")).drop("_"), _truth(units)


def m2(spark, sf):
    """Measures of a scripted tool: restricted and unrestricted wrong reports, with and without repeats, misses, other lines."""
    found, truth = (cut_lineage(d) for d in _reports(spark, sf))
    single = confusion.once(found)
    counts = {"labels": truth, "reports": found, "reports_once": single, "tp": confusion.tp(found, truth), "missed": confusion.fn(found, truth), "fp": confusion.fp(found, truth), "fp_once": confusion.fp(single, truth), "fp_anywhere": confusion.fp(found, truth, False), "other_line": confusion.mismatch(single, truth)}
    rows = reduce(DataFrame.unionByName, [d.select("category", F.lit(k).alias("k")) for k, d in counts.items()])
    return rows.groupBy("category").agg(*(F.count_if(F.col("k") == k).alias(k) for k in counts))


def s23(spark, sf):
    """Wrong reports of the scripted tool, and repeats of right ones, by category and cause."""
    found, _ = _reports(spark, sf)
    return review.causes(found.where("cause IS NOT NULL"))


def w25_published(spark, sf):
    p = published.analysers(spark)
    total = p.groupBy("tool").agg(*(F.sum(c).alias(c) for c in ("labels", "tp", "fp"))).withColumn("category", F.lit("total"))
    return confusion.rates(p.unionByName(total)).select("tool", "category", "labels", "tp", "fp", "prec", "rec")


def _counts(spark, sf) -> DataFrame:
    """``tool, category, tp, fp``: a document labelled of low quality is a report by its source on its language, right if it is toxic too."""
    d = table(spark, sf, "documents").select("doc_id", F.col("source").alias("tool"), F.col("lang").alias("category"))
    low, toxic = F.col("quality") == 0, F.col("toxic") == 1
    return d.join(table(spark, sf, "labels"), "doc_id").groupBy("tool", "category").agg(F.count_if(low & toxic).alias("tp"), F.count_if(low & ~toxic).alias("fp"))


def w25_coverage(spark, sf):
    """Coverage as of the published table, taken of the sources' reports."""
    return confusion.coverage(_counts(spark, sf)).select("tool", "categories", "tp", F.col("place").cast("long").alias("place"))


def w08_published(spark, sf):
    """Totals and precision as of the published table, taken of the sources' reports."""
    p = _counts(spark, sf).groupBy("tool").agg(F.sum("tp").alias("tp"), F.sum("fp").alias("fp"))
    return p.withColumn("prec", F.round(F.try_divide(F.col("tp").cast("double"), F.col("tp") + F.col("fp")), 4))


def w26(spark, sf):
    """Rates at each level of cutting; every distinct program is checked once and counts for all its units."""
    rows = []
    count = lambda d, name: d.agg(F.coalesce(F.sum("n"), F.lit(0)).alias(name))
    for level in T.LEVELS:
        units = cut_lineage(derive.kinds(table(spark, sf, "part"), level))
        truth = units.where("weak").select("unit_id", "rule_id", "category", "line", "n")
        found = cut_lineage(local.evaluate_units(units).where("rule_id IS NOT NULL").select("unit_id", "rule_id", "category", "line"))
        wrong = confusion.fp(found, truth, False).join(units.select("unit_id", "category", "n"), ["unit_id", "category"])
        counts = count(truth, "labels").join(count(confusion.tp(found, truth), "tp")).join(count(wrong, "fp"))
        rows.append(confusion.rates(counts).select(F.lit(level).alias("level"), "tp", "fp", "prec", "rec"))
    return reduce(DataFrame.unionByName, rows)


DAMAGES = ("intact", "no semicolons", "left-out code", "no header")


def _damaged(code, function):
    return {
        "intact": code,
        "no semicolons": F.regexp_replace(code, r"(?m);([ \t]*(?://[^\n]*)?)$", "$1"),
        "left-out code": F.regexp_replace(code, r"(?m)\{$", "{\n  ..."),
        "no header": function,
    }


def w27(spark, sf):
    """Texts that each parser reads, by damage; every distinct program is parsed once and counts for all its units."""
    units = derive.kinds(table(spark, sf, "part"))
    bodies = derive.kinds(table(spark, sf, "part"), "function").select("unit_id", F.col("code").alias("function"))
    both = units.select("unit_id", "code", "n").join(bodies, "unit_id")
    rows = both.select("n", F.inline(F.array(*(F.struct(F.lit(k).alias("mutation"), c.alias("code")) for k, c in _damaged(F.col("code"), F.col("function")).items()))))
    strict = F.udf(lambda c: frontend.parseable(c, "strict"), "boolean")
    lenient = F.udf(lambda c: frontend.parseable(c), "boolean")
    flags = rows.repartition(int(spark.conf.get("spark.sql.shuffle.partitions"))).select("mutation", "n", strict("code").alias("strict_ok"), lenient("code").alias("lenient_ok"))
    times = lambda ok: F.sum(F.when(ok, F.col("n")).otherwise(0))
    return flags.groupBy("mutation").agg(times(F.col("strict_ok")).alias("strict_ok"), times(F.col("lenient_ok")).alias("lenient_ok"), times(F.col("lenient_ok") & ~F.col("strict_ok")).alias("gain"))


def _study(spark, sf):
    """Snippets, distinct programs and the stages; snippets and units without an event of their number are left out."""
    when = table(spark, sf, "events").select("event_id", "ts")
    s = derive.snippets(table(spark, sf, "benchmark")).withColumnRenamed("unit_id", "snippet_id")
    s = s.join(when.where("event_id % 25 = 0").select((F.col("event_id") / 25).cast("long").alias("snippet_id"), F.col("ts").alias("posted_at")), "snippet_id")
    s = cut_lineage(s.select("snippet_id", "code", "posted_at", "rule_id", "weak"))
    rows = derive.unit_rows(table(spark, sf, "part")).join(when.select(F.col("event_id").alias("id"), F.col("ts").alias("deployed_at")), "id")
    programs, units = derive.shared(cut_lineage(rows))
    programs = cut_lineage(programs.select(F.col("unit_id").alias("text_id"), "code", "rule_id", "weak"))
    return s, programs, pipeline.run(s, units, texts=programs)


def w28(spark, sf):
    s, _, stages = _study(spark, sf)
    return pipeline.funnel(stages, s)


def w29(spark, sf):
    _, _, stages = _study(spark, sf)
    f = stages["findings"]
    # Snippets and units are counted apart, so no pair of them is needed.
    return funnel.categories(f.select("category", "snippet_id").distinct().unionByName(pipeline.reached(f, stages["units"], "category"), allowMissingColumns=True))


def w30(spark, sf):
    s, programs, stages = _study(spark, sf)
    findings = pipeline.later(stages["findings"].select("snippet_id", "text_id", "posted_at", "rule_id", "category"), stages["units"])
    chosen = review.sample(findings, 100)
    reviewed = chosen.join(s.select("snippet_id", F.col("rule_id").alias("sr"), F.col("weak").alias("sw")), "snippet_id").join(programs.select("text_id", F.col("rule_id").alias("ur"), F.col("weak").alias("uw")), "text_id")
    reviewed = reviewed.select((F.col("sr") == F.col("ur")).alias("clone_ok"), (F.col("sw") & (F.col("sr") == F.col("rule_id"))).alias("snippet_ok"), (F.col("uw") & (F.col("ur") == F.col("rule_id"))).alias("unit_ok"))
    return review.contingency(reviewed)


def w30_labels(spark, sf):
    """The given two-by-two table of labelled documents."""
    return table(spark, sf, "labels").groupBy(F.col("quality").cast("long").alias("quality"), F.col("toxic").cast("long").alias("toxic")).agg(F.count("*").alias("n"))


def _expected() -> str:
    rows = []
    for i, t in enumerate(T.TEMPLATES):
        if t.weak:
            rows += [f"({i}, {m}, '{t.rule_id}', '{t.category}', {T.weak_line(T.render(i, m))})" for m in range(len(T.MUTATIONS))]
    return f"(VALUES {', '.join(rows)}) AS x(template, mutation, rule_id, category, line)"


def _scripted() -> str:
    rows = []
    for i, t in enumerate(T.TEMPLATES):
        rows += [f"({i}, {m}, {t.weak}, '{t.category}', {T.weak_line(T.render(i, m)) if t.weak else 0})" for m in range(len(T.MUTATIONS))]
    return f"""u AS (SELECT p_partkey AS id, weak, category, line FROM part JOIN (VALUES {', '.join(rows)}) AS x(template, mutation, weak, category, line) ON p_partkey % {len(T.TEMPLATES)} = template AND coalesce(p_size, 0) % 6 = mutation),
r AS (SELECT id, category, CASE WHEN NOT weak THEN 'mitigated' WHEN id % 5 = 0 THEN 'other line' WHEN id % 7 = 0 THEN 'repeated' END AS cause, CASE WHEN id % 7 = 0 THEN 2 ELSE 1 END AS n FROM u WHERE CASE WHEN weak THEN id % 11 <> 0 ELSE id % 3 = 0 END)"""


_COUNTS = "SELECT source AS tool, lang AS category, count(*) FILTER (quality = 0 AND toxic = 1) AS tp, count(*) FILTER (quality = 0 AND toxic <> 1) AS fp FROM documents JOIN labels USING (doc_id) GROUP BY ALL"
_PUBLISHED = " UNION ALL ".join(f"SELECT '{t}' AS tool, '{c}' AS category, {n}::BIGINT AS labels, {x.split('/')[0]}::BIGINT AS tp, {x.split('/')[1]}::BIGINT AS fp" for c, (n, cells) in published.ANALYSERS.items() for t, x in zip(published.TOOLS, cells.split(), strict=True))

QUERIES = {
    "W08_class_tp_fp": w08,
    "W08_published_totals": w08_published,
    "W24_rule_findings": w24,
    "W25_rule_by_tool_table": w25,
    "W25_published_rates": w25_published,
    "W25_published_coverage": w25_coverage,
    "M2_wrong_reports": m2,
    "S23_fp_causes": s23,
    "W26_functions_statements": w26,
    "W27_parse_gain": w27,
    "W28_reuse_study": w28,
    "W29_category_distribution": w29,
    "W30_review_sample": w30,
    "W30_labelled_table": w30_labels,
}
SQL = {
    "M2_wrong_reports": f"""WITH {_scripted()}, a AS (SELECT category, count(*) FILTER (weak) AS labels, count(*) FILTER (weak AND id % 5 <> 0 AND id % 11 <> 0) AS tp FROM u GROUP BY category),
b AS (SELECT category, sum(n)::BIGINT AS reports, count(*) AS reports_once, coalesce(sum(n) FILTER (cause = 'other line'), 0)::BIGINT AS fp, count(*) FILTER (cause = 'other line') AS fp_once, coalesce(sum(n) FILTER (cause IN ('other line', 'mitigated')), 0)::BIGINT AS fp_anywhere FROM r GROUP BY category)
SELECT category, labels, reports, reports_once, tp, labels - tp AS missed, fp, fp_once, fp_anywhere, fp_once AS other_line FROM a JOIN b USING (category)""",
    "S23_fp_causes": f"WITH {_scripted()} SELECT category, cause, sum(n)::BIGINT AS n FROM r WHERE cause IS NOT NULL GROUP BY ALL",
    "W08_published_totals": f"SELECT tool, sum(tp)::BIGINT AS tp, sum(fp)::BIGINT AS fp, round(sum(tp) / nullif(sum(tp) + sum(fp), 0), 4) AS prec FROM ({_COUNTS}) GROUP BY tool",
    "W24_rule_findings": f"SELECT p_partkey AS unit_id, rule_id, category, line::BIGINT AS line FROM part JOIN {_expected()} ON p_partkey % {len(T.TEMPLATES)} = template AND p_size % 6 = mutation",
    "W25_published_rates": f"WITH p AS ({_PUBLISHED}), a AS (SELECT * FROM p UNION ALL SELECT tool, 'total', sum(labels)::BIGINT, sum(tp)::BIGINT, sum(fp)::BIGINT FROM p GROUP BY tool) SELECT *, round(tp / nullif(tp + fp, 0), 6) AS prec, round(tp / nullif(labels, 0), 6) AS rec FROM a",
    "W25_published_coverage": f"SELECT tool, categories, tp, rank() OVER (ORDER BY tp DESC) AS place FROM (SELECT tool, count(*) FILTER (tp > 0) AS categories, sum(tp)::BIGINT AS tp FROM ({_COUNTS}) WHERE category <> 'total' GROUP BY tool)",
    "W27_parse_gain": "WITH n AS (SELECT count(*) AS n FROM part) SELECT m AS mutation, CASE WHEN m = 'intact' THEN n ELSE 0 END AS strict_ok, n AS lenient_ok, CASE WHEN m = 'intact' THEN 0 ELSE n END AS gain FROM n, (SELECT unnest(['intact', 'no semicolons', 'left-out code', 'no header']) AS m)",
    "W30_labelled_table": "SELECT quality::BIGINT AS quality, toxic::BIGINT AS toxic, count(*) AS n FROM labels GROUP BY ALL",
}
