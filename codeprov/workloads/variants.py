"""Variants, baselines and measures that have no workload of their own."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.baselines import embedding, exact
from codeprov.clone import candidates, fingerprint, match
from codeprov.clone.fuzzyhash import hash_sequence
from codeprov.clone.score import DIRECTIONS, order_free, order_free_bounded
from codeprov.corpus import derive
from codeprov.functions.register import t_pvalue
from codeprov.graph import local
from codeprov.measure import cost, describe, funnel, spearman
from codeprov.session import cut_lineage, table
from codeprov.study import collect, popularity, review
from codeprov.study.source_profile import fingerprints
from codeprov.workloads import clones, hashes


def _prints(spark, sf, name, id):
    return cut_lineage(fingerprint.build(table(spark, sf, name), id))


def hash_variants(spark, sf):
    """Fingerprint length of each item by each hash, and of the undivided text."""
    t = table(spark, sf, "benchmark")
    out = [fingerprint.build(t, "item_id", variant=v).select(F.lit(v).alias("variant"), F.col("id").alias("item_id"), F.col("len").cast("long").alias("len")) for v in ("token64", "ctph", "fixed7")]
    whole = t.select(F.lit("whole text").alias("variant"), "item_id", F.length(hash_sequence(F.coalesce("text", F.lit("")))).cast("long").alias("len"))
    return reduce(DataFrame.unionByName, [*out, whole])


def directions(spark, sf):
    """The order-free score of candidates in each direction, and with equal maxima taken once."""
    q, t = _prints(spark, sf, "benchmark", "item_id"), _prints(spark, sf, "documents", "doc_id")
    pairs = candidates.retrieve(q, t).join(q.select(F.col("id").alias("query_id"), F.col("subs").alias("q")), "query_id").join(t.select(F.col("id").alias("target_id"), F.col("subs").alias("t")), "target_id")
    scores = [F.round(order_free("q", "t", d), 6).alias(d) for d in DIRECTIONS]
    return pairs.select(F.col("query_id").alias("item_id"), F.col("target_id").alias("doc_id"), *scores, F.round(order_free("q", "t", collapse_equal=True), 6).alias("as_set"), order_free_bounded("q", "t", 0.7).isNotNull().alias("kept"))


def exact_hash(spark, sf):
    d = table(spark, sf, "documents")
    return exact.hash_match(d, d, "doc_id", "doc_id").where("query_id < target_id")


def compression(spark, sf):
    return cost.compression(table(spark, sf, "documents"), _prints(spark, sf, "documents", "doc_id"), "doc_id")


def text_vectors(spark, sf):
    """Cosine pairs of hashed word counts of the items."""
    return embedding.cosine_pairs(embedding.token_vectors(table(spark, sf, "benchmark"), "item_id"), 0.9).select("a", "b", F.round("cosine", 6).alias("cosine"))


def minhash_recall(spark, sf):
    """Share of the exact candidates of W03 that the hashed strategy finds."""
    q, t = _prints(spark, sf, "benchmark", "item_id"), _prints(spark, sf, "documents", "doc_id")
    every = candidates.retrieve(q, t).select("query_id", "target_id", F.lit(1).alias("x"))
    found = candidates.retrieve(q, t, strategy="minhash", bands=32, rows=1).select("query_id", "target_id", F.lit(1).alias("y"))
    return every.join(found, ["query_id", "target_id"], "left").agg(F.count("*").alias("exact"), F.count("y").alias("found"), F.round(F.try_divide(F.count("y").cast("double"), F.count("*")), 6).alias("recall"))


def part_dictionary(spark, sf):
    return fingerprint.dictionary(_prints(spark, sf, "documents", "doc_id")).agg(F.count("*").alias("distinct_parts"), F.sum("df").alias("postings"), F.max("df").alias("most"))


def dedup_scopes(spark, sf):
    c = table(spark, sf, "conversations").select("conv_id", "turn", "text", F.col("role").alias("site"), (F.col("conv_id") * 1000 + F.col("turn")).alias("posted_at"))
    rows = [collect.dedup(c, s).groupBy("site").agg(F.count("*").alias("n")).withColumn("scope", F.lit(s)) for s in ("per_source", "global")]
    return reduce(DataFrame.unionByName, rows).groupBy("scope").agg(F.sum("n").alias("n"))


def posts_until(spark, sf):
    p = table(spark, sf, "events").select("event_id", F.col("event_type").alias("tag"), F.col("ts").alias("created_at"))
    return collect.posts(p, "view", F.lit("2024-01-10").cast("timestamp_ntz")).select("event_id")


def duplicate_units(spark, sf):
    once, _ = collect.dedup_units(derive.units(table(spark, sf, "part")).select("unit_id", "code"))
    return once.agg(F.count("*").alias("codes"), F.sum("unit_id").alias("ids"))


def most_viewed(spark, sf):
    v = table(spark, sf, "events").where("event_type = 'view'").groupBy("user_id").agg(F.count("*").alias("views"))
    return popularity.top(v, 10)


def residue(spark, sf):
    """Units that no mitigated program is similar to; equal programs are searched once."""
    units = cut_lineage(derive.kinds(table(spark, sf, "part")))
    prints = cut_lineage(fingerprints(units, "unit_id"))
    good = units.where("NOT weak AND mutation = 0").select(F.col("unit_id").alias("id"))
    left = review.not_vetted(prints, prints.join(good, "id", "left_semi"))
    return left.join(units.select(F.col("unit_id").alias("id"), "weak", "n"), "id").groupBy("weak").agg(F.sum("n").alias("n"))


def clone_types(spark, sf):
    """Types of clones among the first units of each template, by mutation of the target."""
    units = cut_lineage(derive.units(table(spark, sf, "part")))
    from codeprov.lang import frontend

    kind = F.udf(frontend.clone_type, "string")
    a = units.where("mutation = 0").groupBy("template").agg(F.min_by("code", "unit_id").alias("q"))
    b = units.where("mutation > 0").groupBy("template", "mutation").agg(F.min_by("code", "unit_id").alias("t"))
    return a.join(b, "template").select("template", "mutation", kind("q", "t").alias("type"))


def ablations(spark, sf):
    """Self-clones of derived units under each choice of canonical text; equal fingerprints are searched once and counted in full."""
    units = cut_lineage(derive.kinds(table(spark, sf, "part")))
    weight = units.select(F.col("unit_id").alias("id"), "n")

    def pairs(**options):
        reps, members = match.collapse(fingerprints(units, "unit_id", **options))
        n = cut_lineage(members.join(weight, "id").groupBy("rep").agg(F.sum("n").alias("n")))
        a, b = n.withColumnsRenamed({"rep": "query_id", "n": "a"}), n.withColumnsRenamed({"rep": "target_id", "n": "b"})
        own = F.when(F.col("query_id") == F.col("target_id"), F.col("a")).otherwise(0)
        return match.class_clones(reps, match.CONSERVATIVE).join(a, "query_id").join(b, "target_id").agg(F.coalesce(F.sum(F.col("a") * F.col("b") - own), F.lit(0)).alias("pairs"))

    choices = {"canonical": {}, "names kept": {"names": "keep"}, "literals kept": {"literals": "keep"}, "numbers masked": {"numbers": "mask"}, "visibility kept": {"drop_visibility": False}}
    rows = [pairs(**o).select(F.lit(k).alias("choice"), "pairs") for k, o in choices.items()]
    return reduce(DataFrame.unionByName, rows)


def phases(spark, sf):
    """Units settled in each phase under a small budget, with and without a schedule."""
    units = derive.units(table(spark, sf, "part"))
    rows = []
    for name, schedule in (("one phase", ()), ("two phases", (16, 8, 4, 2))):
        found = local.evaluate_units(units, budget=150, hop_schedule=schedule)
        state = found.groupBy("unit_id").agg(F.max("phase").alias("phase"), F.max("status").alias("status"))
        rows.append(funnel.phases(state).withColumn("run", F.lit(name)))
    return reduce(DataFrame.unionByName, rows)


def p_values(spark, sf):
    """Spearman per class with its two-sided p."""
    o = table(spark, sf, "orders").select(F.col("o_orderpriority").alias("class"), F.col("o_totalprice").alias("x"), F.col("o_custkey").cast("double").alias("y"))
    return spearman.spearman(o, "x", "y", ["class"]).select("class", "n", F.round("rho", 6).alias("rho"), F.round(t_pvalue("rho", "n"), 6).alias("p"))


def level_shares(spark, sf):
    """Levels of derived texts of all three cuts."""
    from codeprov.lang import frontend

    level = F.udf(frontend.level_of, "string")
    texts = reduce(DataFrame.unionByName, [derive.units(table(spark, sf, "part"), k).select("code") for k in ("unit", "function", "statement")])
    return describe.shares(texts.select(level("code").alias("level")), "level")


QUERIES = {
    "C7_hash_variants": hash_variants,
    "C15_directions": directions,
    "C20_clone_types": clone_types,
    "B14_text_vectors": text_vectors,
    "B18_exact_hash": exact_hash,
    "B19_ablations": ablations,
    "B21_phases": phases,
    "B23_minhash_recall": minhash_recall,
    "K6_level_shares": level_shares,
    "M17_compression": compression,
    "R10_part_dictionary": part_dictionary,
    "S1_posts_until": posts_until,
    "S5_dedup_scopes": dedup_scopes,
    "S6_duplicate_units": duplicate_units,
    "S16_p_values": p_values,
    "S25_most_viewed": most_viewed,
    "S26_not_vetted": residue,
}
SQL = {
    "C7_hash_variants": hashes.lengths(),
    "B18_exact_hash": "SELECT a.doc_id AS query_id, b.doc_id AS target_id FROM documents a JOIN documents b ON a.text = b.text AND a.doc_id < b.doc_id",
    "M17_compression": f"WITH {clones.prints('t', 'documents', 'doc_id')} SELECT round(avg(length(array_to_string(subs, '.')) / length(text)), 6) AS ratio FROM t JOIN documents ON id = doc_id WHERE length(text) > 0",
    "R10_part_dictionary": f"WITH {clones.prints('t', 'documents', 'doc_id')} SELECT count(*) AS distinct_parts, sum(n)::BIGINT AS postings, max(n) AS most FROM (SELECT s, count(*) AS n FROM (SELECT id, unnest(list_distinct(subs)) AS s FROM t) GROUP BY s)",
    "S1_posts_until": "SELECT event_id FROM events WHERE event_type = 'view' AND ts <= TIMESTAMP '2024-01-10'",
    "S5_dedup_scopes": "SELECT 'per_source' AS scope, count(*) AS n FROM (SELECT DISTINCT role, text FROM conversations) UNION ALL SELECT 'global', count(DISTINCT text) FROM conversations",
    "S25_most_viewed": "SELECT user_id, count(*) AS views FROM events WHERE event_type = 'view' GROUP BY user_id ORDER BY views DESC, user_id LIMIT 10",
    "C15_directions": f"WITH {clones.prints('q', 'benchmark', 'item_id')}, {clones.prints('t', 'documents', 'doc_id')}, {clones.grams('qg', 'q', 3)}, {clones.grams('tg', 't', 3)}, {clones.shared('c', 'qg', 'tg', 0.5)}, {clones.scores('s', 'c', 'q', 't')}, d AS (SELECT target_id AS query_id, query_id AS target_id FROM c), {clones.scores('r', 'd', 't', 'q')} SELECT s.query_id AS item_id, s.target_id AS doc_id, round(s.score, 6) AS forward, round(r.score, 6) AS backward, round(greatest(s.score, r.score), 6) AS max, round(least(s.score, r.score), 6) AS min, round((s.score + r.score) / 2, 6) AS mean, (SELECT round(avg(b), 6) FROM (SELECT DISTINCT round(best, 9) AS b FROM (SELECT k, max(100.0 * (1 - levenshtein(u, v) / greatest(length(u), length(v)))) AS best FROM (SELECT unnest(range(len(x.subs))) AS k, x.subs AS qs, y.subs AS ts FROM q x, t y WHERE x.id = s.query_id AND y.id = s.target_id) z, LATERAL (SELECT qs[k + 1] AS u, unnest(ts) AS v) GROUP BY k))) AS as_set, s.score >= 70 AS kept FROM s JOIN r ON r.query_id = s.target_id AND r.target_id = s.query_id",
}
