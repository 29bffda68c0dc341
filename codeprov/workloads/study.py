"""Workloads of the reuse study and of the graph engine on the given tables."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from codeprov.clone import match
from codeprov.graph import closure, pattern, validate
from codeprov.measure import describe, funnel, spearman
from codeprov.session import cut_lineage, table
from codeprov.study import collect, popularity, temporal
from codeprov.workloads import clones

LANGUAGE = "en"


def _site(url="url"):
    return F.regexp_extract(url, r"^[a-z]+://[^/?#]+/([^/?#]*)", 1)


def _stages(spark, sf) -> DataFrame:
    posts = table(spark, sf, "pages").select(F.col("page_id").alias("post_id"), _site().alias("site"), F.col("html").alias("body"))
    s = collect.extract_snippets(posts, tags=("p", "li"))
    hit = F.coalesce(collect.keyword_hits(F.col("text"), collect.exclusive(LANGUAGE)) >= 1, F.lit(False))
    long = F.coalesce(F.size(collect.words(F.col("text"))) >= 3, F.lit(False))
    s = s.select("site", "post_id", "position", "text", F.col("text").isNotNull().alias("snippet"), hit.alias("in_language"), long.alias("parseable"))
    good = s.where("in_language AND parseable").groupBy("site", "text").agg(F.min(F.struct("post_id", "position")).alias("k"))
    good = good.select("site", F.col("k.post_id").alias("post_id"), F.col("k.position").alias("position"), F.lit(True).alias("first"))
    return s.join(good, ["site", "post_id", "position"], "left").withColumn("first", F.coalesce("first", F.lit(False)))


def w13(spark, sf):
    return funnel.collection(_stages(spark, sf))


def w14(spark, sf):
    docs = table(spark, sf, "documents").select("lang", "text")
    flags = docs.select("lang", *((collect.keyword_hits(F.col("text"), collect.exclusive(k)) >= 1).alias(k) for k in collect.KEYWORDS))
    rows = flags.select("lang", F.inline(F.array(*(F.struct(F.lit(k).alias("k"), F.col(k).alias("kept")) for k in collect.KEYWORDS))))
    own = F.col("lang") == F.col("k")
    g = rows.groupBy(F.col("k")).agg(F.count_if(F.col("kept") & own).alias("kept_true"), F.count_if(F.col("kept") & ~own).alias("kept_false"), F.count_if(~F.col("kept") & own).alias("dropped_true"))
    t = F.col("kept_true").cast("double")
    return g.select(F.col("k").alias("lang"), "kept_true", "kept_false", "dropped_true", F.round(F.try_divide(t, F.col("kept_true") + F.col("kept_false")), 6).alias("prec"), F.round(F.try_divide(t, F.col("kept_true") + F.col("dropped_true")), 6).alias("rec"))


def w15(spark, sf):
    docs = table(spark, sf, "documents")
    lines = F.size(F.split("text", "\n"))
    level = F.when(lines >= 5, "unit").when(lines >= 2, "function").otherwise("statement")
    shares = describe.shares(docs.where("text IS NOT NULL").select(level.alias("metric")), "metric").select("metric", F.col("share").alias("value"))
    return describe.loc(docs).unionByName(shares)


def w16(spark, sf):
    orders = table(spark, sf, "orders")
    last = orders.agg(F.max("o_orderdate").alias("m")).first()["m"]
    if last is None:
        return describe.versions(orders, "o_orderpriority", "o_orderdate", F.lit(None))
    return describe.versions(orders, "o_orderpriority", "o_orderdate", F.lit(last) - F.expr("INTERVAL '60' DAY"))


def _matches(spark, sf) -> DataFrame:
    found = match.find_clones(clones._items(spark, sf), clones._documents(spark, sf))
    when = table(spark, sf, "events").select("event_id", "ts")
    posted = when.where("event_id % 25 = 0").select((F.col("event_id") / 25).cast("long").alias("snippet_id"), F.col("ts").alias("posted_at"))
    deployed = when.select(F.col("event_id").alias("unit_id"), F.col("ts").alias("deployed_at"))
    out = found.select(F.col("query_id").alias("snippet_id"), F.col("target_id").alias("unit_id")).join(posted, "snippet_id").join(deployed, "unit_id")
    codes = table(spark, sf, "documents").select(F.col("doc_id").alias("unit_id"), F.sha2("text", 256).alias("code_hash"))
    return cut_lineage(out.join(codes, "unit_id"))


def w17(spark, sf):
    c = temporal.classify(_matches(spark, sf))
    return c.select(F.col("snippet_id").alias("item_id"), "n_all", "n_after", "is_disseminator", "is_source", F.unix_micros(F.col("first_unit").cast("timestamp")).alias("first_unit"))


def w17_units(spark, sf):
    return funnel.units_by_class(temporal.with_class(_matches(spark, sf)))


def w18(spark, sf):
    views = table(spark, sf, "events").where("event_type = 'view'").groupBy(F.col("user_id").alias("snippet_id")).agg(F.count("*").alias("views"))
    t = popularity.table(_matches(spark, sf), views)
    return spearman.spearman(t, "views", "adopters", ["class"]).select("class", "n", F.round("rho", 6).alias("rho"))


def w19(spark, sf):
    li = table(spark, sf, "lineitem")
    o = table(spark, sf, "orders")
    parts = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_custkey").agg(F.count_distinct("l_partkey").alias("y"))
    counts = o.groupBy("o_custkey").agg(F.count("*").alias("x")).join(parts, "o_custkey").select(F.lit("customer").alias("class"), F.col("x").cast("double").alias("x"), F.col("y").cast("double").alias("y"))
    sold = li.groupBy("l_partkey").agg(F.sum("l_quantity").alias("y"))
    price = table(spark, sf, "part").join(sold, F.col("p_partkey") == F.col("l_partkey")).select(F.lit("part").alias("class"), F.col("p_retailprice").alias("x"), "y")
    return spearman.spearman(counts.unionByName(price), "x", "y", ["class"]).select("class", "n", F.round("rho", 6).alias("rho"))


def w19_pearson(spark, sf):
    c = table(spark, sf, "orders").groupBy("o_custkey").agg(F.count("*").cast("double").alias("x"), F.sum("o_totalprice").alias("y"))
    return spearman.pearson(c, "x", "y", []).select("n", F.round("r", 6).alias("r"))


def event_graph(spark, sf) -> tuple[DataFrame, DataFrame]:
    """Node = event; EOG = next event of the user; DFG = next event of the user with the same ``k``."""
    e = table(spark, sf, "events").select(F.col("user_id").alias("unit_id"), F.col("event_id").alias("node_id"), "event_type", "value", "ts", F.get_json_object("props", "$.k").alias("k"))
    order = Window.partitionBy("unit_id").orderBy("ts", "node_id")
    flow = Window.partitionBy("unit_id", "k").orderBy("ts", "node_id")
    step = e.select("unit_id", F.col("node_id").alias("src"), F.lead("node_id").over(order).alias("eog"), F.when(F.col("k").isNotNull(), F.lead("node_id").over(flow)).alias("dfg"))
    edges = step.select("unit_id", "src", F.inline(F.array(F.struct(F.col("eog").alias("dst"), F.lit("EOG").alias("kind")), F.struct(F.col("dfg").alias("dst"), F.lit("DFG").alias("kind"))))).where("dst IS NOT NULL")
    return e, edges


def _typed(nodes, kind):
    return nodes.where(F.col("event_type") == kind).select("unit_id", "node_id")


def _base(nodes, edges, hops):
    ends = _typed(nodes, "purchase").withColumnRenamed("node_id", "dst")
    return closure.reach(edges, "DFG", _typed(nodes, "signup"), hops).join(ends, ["unit_id", "dst"], "left_semi").select("unit_id", "src", "dst")


def _between(kind):
    def part(nodes, edges, hops):
        """Pairs of the base with an event of the kind strictly between them in time."""
        at = nodes.select("unit_id", "node_id", "ts")
        b = _base(nodes, edges, hops).join(at.withColumnsRenamed({"node_id": "src", "ts": "t0"}), ["unit_id", "src"]).join(at.withColumnsRenamed({"node_id": "dst", "ts": "t1"}), ["unit_id", "dst"])
        m = nodes.where(F.col("event_type") == kind).select("unit_id", F.col("ts").alias("t"))
        return b.join(m, (b["unit_id"] == m["unit_id"]) & (m["t"] > b["t0"]) & (m["t"] < b["t1"]), "left_semi").select("unit_id", "src", "dst")

    return part


def _grows(nodes, edges, hops):
    v = nodes.select("unit_id", "node_id", "value")
    return _base(nodes, edges, hops).join(v.withColumnsRenamed({"node_id": "src", "value": "v0"}), ["unit_id", "src"]).join(v.withColumnsRenamed({"node_id": "dst", "value": "v1"}), ["unit_id", "dst"]).where("v1 > v0").select("unit_id", "src", "dst")


EVENT_RULE = pattern.Rule("EV1", "event flow", _base, ("src", "dst"), (_grows, _between("view")), (_between("error"),))


def w20(spark, sf):
    nodes, edges = event_graph(spark, sf)
    return pattern.evaluate(nodes, edges, [EVENT_RULE]).select(F.col("unit_id").alias("user_id"), "src", "dst", F.lit("signup").alias("src_type"), F.lit("purchase").alias("dst_type"))


def w21(spark, sf):
    nodes, edges = event_graph(spark, sf)
    r = closure.reach(edges, "EOG", _typed(nodes, "signup"), 8)
    limits = spark.createDataFrame([(1,), (2,), (4,), (8,)], "max_hops long")
    return limits.join(r, F.col("hops") <= F.col("max_hops"), "left").groupBy("max_hops").agg(F.count("src").alias("pairs"))


def k18(spark, sf):
    """Signups followed within eight events of the user by a purchase, with an error on the way."""
    nodes, edges = event_graph(spark, sf)
    edges = cut_lineage(edges)
    ends = _typed(nodes, "purchase").withColumnRenamed("node_id", "dst")
    pairs = closure.reach(edges, "EOG", _typed(nodes, "signup"), 8).join(ends, ["unit_id", "dst"], "left_semi")
    return pattern.on_path(edges, "EOG", pairs, _typed(nodes, "error"), 8).select(F.col("unit_id").alias("user_id"), "src", "dst")


def k19(spark, sf):
    """Last events of users; an error there takes the place of a rollback."""
    nodes, edges = event_graph(spark, sf)
    labelled = nodes.withColumn("labels", F.when(F.col("event_type") == "error", F.array(F.lit("Rollback"))).otherwise(F.array(F.col("event_type"))))
    kept = pattern.exits(labelled, edges).withColumn("persisting", F.lit(True))
    return pattern.exits(labelled, edges, persisting=False).join(kept, ["unit_id", "node_id"], "left").select(F.col("unit_id").alias("user_id"), F.col("node_id").alias("event_id"), F.coalesce("persisting", F.lit(False)).alias("persisting"))


def m15(spark, sf):
    """Snippets with clones, and the share with a clone among documents labelled of low quality."""
    low = table(spark, sf, "labels").where("quality = 0").select(F.col("doc_id").alias("unit_id"), F.lit(True).alias("low")).distinct()
    found = _matches(spark, sf).join(low, "unit_id", "left")
    return funnel.validated_share(found.select("snippet_id", F.coalesce("low", F.lit(False)).alias("validated")))


def s27(spark, sf):
    """Links of each class before and after equal texts are taken once."""
    c = cut_lineage(temporal.with_class(_matches(spark, sf)))
    classes = {"all": c, "disseminator": c.where("is_disseminator AND later"), "source": c.where("is_source")}
    rows = [funnel.candidates(d.select("unit_id", "code_hash").distinct()).select(F.lit(k).alias("class"), "units", "codes") for k, d in classes.items()]
    return reduce(DataFrame.unionByName, rows)


BUDGET, SCHEDULE = 40, (16, 8, 4, 2)


def w22(spark, sf):
    nodes, edges = event_graph(spark, sf)
    findings, status = validate.two_phase(nodes, edges, [EVENT_RULE], "DFG", _typed(nodes, "signup"), BUDGET, SCHEDULE)
    n = findings.groupBy("unit_id").agg(F.count("*").alias("findings"))
    return status.join(n, "unit_id", "left").select(F.col("unit_id").alias("user_id"), F.col("phase").cast("long").alias("phase"), "status", F.coalesce("findings", F.lit(0)).alias("findings"))


def w23(spark, sf):
    """Customers that reach a supplier of their own nation through orders, unless a line of the pair was returned."""
    c, o, li, s = (table(spark, sf, t) for t in ("customer", "orders", "lineitem", "supplier"))
    path = o.join(li, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_custkey", "l_suppkey").agg(F.count("*").alias("paths"), F.bool_or(F.col("l_returnflag") == "R").alias("returned"))
    own = path.where("NOT returned").join(c, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(s), (F.col("l_suppkey") == F.col("s_suppkey")) & (F.col("c_nationkey") == F.col("s_nationkey")))
    return own.select(F.col("c_custkey").alias("custkey"), F.col("s_suppkey").alias("suppkey"), "paths")


def _hits(words: list[str]) -> str:
    return f"len(list_intersect(regexp_split_to_array(lower(text), '[^\\p{{L}}\\p{{N}}]+'), {words})) >= 1"


_CUTS = "'(?s)<(?:p|li)\\b[^>]*>(.*?)</(?:p|li)>'"
_PLAIN = "regexp_replace(b, '<[^>]*>', '', 'g')"
for _e, _s in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "''"), ("&amp;", "&")):
    _PLAIN = f"replace({_PLAIN}, '{_e}', '{_s}')"
_SITE = r"regexp_extract(url, '^[a-z]+://[^/?#]+/([^/?#]*)', 1)"
_EV = """e AS (SELECT user_id AS unit_id, event_id AS node_id, event_type, value, ts, json_extract_string(props, '$.k') AS k FROM events),
eog AS (SELECT * FROM (SELECT unit_id, node_id AS src, lead(node_id) OVER (PARTITION BY unit_id ORDER BY ts, node_id) AS dst FROM e) WHERE dst IS NOT NULL),
dfg AS (SELECT * FROM (SELECT unit_id, node_id AS src, lead(node_id) OVER (PARTITION BY unit_id, k ORDER BY ts, node_id) AS dst FROM e WHERE k IS NOT NULL) WHERE dst IS NOT NULL)"""
_RULE = _EV + """, r(unit_id, src, dst, hops) AS (SELECT d.unit_id, d.src, d.dst, 1 FROM dfg d JOIN e ON e.node_id = d.src WHERE event_type = 'signup' UNION SELECT r.unit_id, r.src, d.dst, hops + 1 FROM r JOIN dfg d ON d.src = r.dst AND d.unit_id = r.unit_id WHERE hops < 60),
base AS (SELECT DISTINCT r.unit_id, r.src, r.dst, a.ts AS t0, b.ts AS t1, a.value AS v0, b.value AS v1 FROM r JOIN e a ON a.node_id = r.src JOIN e b ON b.node_id = r.dst WHERE b.event_type = 'purchase'),
f AS (SELECT * FROM base WHERE (v1 > v0 OR EXISTS (SELECT 1 FROM e WHERE e.unit_id = base.unit_id AND event_type = 'view' AND ts > t0 AND ts < t1))
  AND NOT EXISTS (SELECT 1 FROM e WHERE e.unit_id = base.unit_id AND event_type = 'error' AND ts > t0 AND ts < t1))"""


def _matches_sql() -> str:
    return f"""{clones.prints('q', 'benchmark', 'item_id')}, {clones.prints('t', 'documents', 'doc_id')}, {clones.grams('qg', 'q', 3)}, {clones.grams('tg', 't', 3)}, {clones.shared('c', 'qg', 'tg', 0.5)}, {clones.scores('s', 'c', 'q', 't')},
m AS (SELECT query_id AS item_id, target_id AS doc_id, p.ts AS posted, d.ts AS deployed, sha256(x.text) AS h FROM s JOIN events p ON p.event_id = query_id * 25 JOIN events d ON d.event_id = target_id JOIN documents x ON x.doc_id = target_id WHERE score >= 70),
k AS (SELECT item_id, posted, count(*) AS n_all, count(*) FILTER (deployed > posted) AS n_after, min(deployed) AS first_unit FROM m GROUP BY ALL)"""


def _rho(source: str) -> str:
    return f"""SELECT class, count(*) AS n, round(corr(rx, ry), 6) AS rho FROM (SELECT class, rank() OVER (PARTITION BY class ORDER BY x) + (count(*) OVER (PARTITION BY class, x) - 1) / 2.0 AS rx, rank() OVER (PARTITION BY class ORDER BY y) + (count(*) OVER (PARTITION BY class, y) - 1) / 2.0 AS ry FROM {source}) GROUP BY class"""


QUERIES = {
    "W13_collection_funnel": w13,
    "W14_keyword_filter": w14,
    "W15_snippet_stats": w15,
    "W16_version_share": w16,
    "W17_temporal_classes": w17,
    "W17_units_by_class": w17_units,
    "W18_popularity_spearman": w18,
    "W19_spearman_large": w19,
    "W19_pearson": w19_pearson,
    "W20_event_flow_rule": w20,
    "W21_reach_bounded": w21,
    "W22_two_phase": w22,
    "W23_star_graph": w23,
    "K18_on_path": k18,
    "K19_exits": k19,
    "M15_validated_share": m15,
    "S27_candidate_codes": s27,
}
SQL = {
    "W13_collection_funnel": f"""WITH b AS (SELECT page_id, {_SITE} AS site, unnest(list_concat(regexp_extract_all(html, {_CUTS}, 1), CASE WHEN len(regexp_extract_all(html, {_CUTS}, 1)) = 0 THEN [NULL] ELSE [] END)) AS b FROM pages),
s AS (SELECT site, page_id, trim({_PLAIN}) AS text FROM b), f AS (SELECT *, coalesce({_hits(collect.exclusive(LANGUAGE))}, false) AS l, coalesce(len(list_filter(regexp_split_to_array(lower(text), '[^\\p{{L}}\\p{{N}}]+'), lambda w: w <> '')) >= 3, false) AS p FROM s),
g AS (SELECT site, count(DISTINCT page_id) AS posts, count(text) AS snippets, count(*) FILTER (l) AS in_language, count(*) FILTER (l AND p) AS parseable, count(DISTINCT text) FILTER (l AND p) AS uniq FROM f GROUP BY site)
SELECT * FROM g UNION ALL SELECT 'total', sum(posts)::BIGINT, sum(snippets)::BIGINT, sum(in_language)::BIGINT, sum(parseable)::BIGINT, sum(uniq)::BIGINT FROM g""",
    "W14_keyword_filter": " UNION ALL ".join(f"SELECT '{k}' AS lang, a AS kept_true, b AS kept_false, c AS dropped_true, round(a / nullif(a + b, 0), 6) AS prec, round(a / nullif(a + c, 0), 6) AS rec FROM (SELECT count(*) FILTER (h AND lang = '{k}') AS a, count(*) FILTER (h AND lang <> '{k}') AS b, count(*) FILTER (NOT h AND lang = '{k}') AS c FROM (SELECT lang, {_hits(collect.exclusive(k))} AS h FROM documents))" for k in collect.KEYWORDS),
    "W15_snippet_stats": r"WITH l AS (SELECT len(string_split(text, chr(10))) AS n FROM documents WHERE text IS NOT NULL), k AS (SELECT CASE WHEN n >= 5 THEN 'unit' WHEN n >= 2 THEN 'function' ELSE 'statement' END AS metric FROM l) SELECT 'min' AS metric, min(n)::DOUBLE AS value FROM l UNION ALL SELECT 'mean', round(avg(n), 6) FROM l UNION ALL SELECT 'median', median(n) FROM l UNION ALL SELECT 'max', max(n) FROM l UNION ALL SELECT metric, round(count(*) / (SELECT count(*) FROM k), 6) FROM k GROUP BY metric",
    "W16_version_share": "WITH g AS (SELECT o_orderpriority AS version, count(*) AS n, count(*) FILTER (o_orderdate >= (SELECT max(o_orderdate) FROM orders) - INTERVAL 60 DAY) AS recent_n FROM orders GROUP BY ALL) SELECT version, n, round(n / sum(n) OVER (), 6) AS share, recent_n, round(recent_n / sum(recent_n) OVER (), 6) AS recent_share FROM g",
    "W17_temporal_classes": f"WITH {_matches_sql()} SELECT item_id, n_all, n_after, n_after > 0 AS is_disseminator, first_unit > posted AS is_source, epoch_us(first_unit)::BIGINT AS first_unit FROM k",
    "W17_units_by_class": f"WITH {_matches_sql()} SELECT count(DISTINCT doc_id) AS any, count(DISTINCT doc_id) FILTER (n_after > 0 AND deployed > m.posted) AS disseminator, count(DISTINCT doc_id) FILTER (first_unit > m.posted) AS source FROM m JOIN k USING (item_id)",
    "W18_popularity_spearman": f"WITH {_matches_sql()}, v AS (SELECT user_id AS item_id, count(*) AS views FROM events WHERE event_type = 'view' GROUP BY ALL), j AS (SELECT m.*, n_after, first_unit FROM m JOIN k USING (item_id)), z AS (SELECT 'all' AS class, item_id, count(DISTINCT h) AS y FROM j GROUP BY ALL UNION ALL SELECT 'disseminator', item_id, count(DISTINCT h) FROM j WHERE n_after > 0 AND deployed > posted GROUP BY ALL UNION ALL SELECT 'source', item_id, count(DISTINCT h) FROM j WHERE first_unit > posted GROUP BY ALL), u AS (SELECT class, coalesce(views, 0) AS x, y FROM z LEFT JOIN v USING (item_id)) {_rho('u')}",
    "W19_spearman_large": f"WITH p AS (SELECT o_custkey, count(DISTINCT l_partkey) AS y FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL), t AS (SELECT 'customer' AS class, x::DOUBLE AS x, y::DOUBLE AS y FROM (SELECT o_custkey, count(*) AS x FROM orders GROUP BY ALL) JOIN p USING (o_custkey) UNION ALL SELECT 'part', p_retailprice, q FROM part JOIN (SELECT l_partkey, sum(l_quantity) AS q FROM lineitem GROUP BY ALL) ON l_partkey = p_partkey) {_rho('t')}",
    "W19_pearson": "SELECT count(*) AS n, round(corr(x, y), 6) AS r FROM (SELECT count(*)::DOUBLE AS x, sum(o_totalprice) AS y FROM orders GROUP BY o_custkey)",
    "W20_event_flow_rule": f"WITH RECURSIVE {_RULE} SELECT unit_id AS user_id, src, dst, 'signup' AS src_type, 'purchase' AS dst_type FROM f",
    "W21_reach_bounded": f"WITH RECURSIVE {_EV}, r(unit_id, src, dst, hops) AS (SELECT d.unit_id, d.src, d.dst, 1 FROM eog d JOIN e ON e.node_id = d.src WHERE event_type = 'signup' UNION ALL SELECT r.unit_id, r.src, d.dst, hops + 1 FROM r JOIN eog d ON d.src = r.dst WHERE hops < 8) SELECT max_hops, (SELECT count(*) FROM r WHERE hops <= max_hops) AS pairs FROM (SELECT unnest([1, 2, 4, 8])::BIGINT AS max_hops)",
    "W22_two_phase": f"""WITH RECURSIVE {_RULE}, p(phase, h) AS (VALUES (0, 1000000), {', '.join(f'({i}, {h})' for i, h in enumerate(SCHEDULE, 1))}),
t AS (SELECT unit_id, src, dst, min(hops) AS hops FROM r GROUP BY ALL), u AS (SELECT DISTINCT unit_id FROM e),
c AS (SELECT u.unit_id, phase, h, count(t.src) AS cost FROM u CROSS JOIN p LEFT JOIN t ON t.unit_id = u.unit_id AND t.hops <= h GROUP BY ALL),
w AS (SELECT unit_id, min(phase) AS phase, max(h) AS h FROM c WHERE cost <= {BUDGET} GROUP BY ALL)
SELECT u.unit_id AS user_id, w.phase::BIGINT AS phase, CASE WHEN w.phase IS NULL THEN 'budget_exceeded' ELSE 'ok' END AS status, (SELECT count(*) FROM f JOIN t USING (unit_id, src, dst) WHERE f.unit_id = u.unit_id AND t.hops <= w.h) AS findings FROM u LEFT JOIN w USING (unit_id)""",
    "W23_star_graph": "SELECT c_custkey AS custkey, s_suppkey AS suppkey, count(*) AS paths FROM customer JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN supplier ON s_suppkey = l_suppkey AND s_nationkey = c_nationkey GROUP BY ALL HAVING NOT bool_or(l_returnflag = 'R')",
    "K18_on_path": "WITH o AS (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM events) SELECT a.user_id, a.event_id AS src, b.event_id AS dst FROM o a JOIN o b ON a.user_id = b.user_id AND b.k > a.k AND b.k <= a.k + 8 WHERE a.event_type = 'signup' AND b.event_type = 'purchase' AND EXISTS (SELECT 1 FROM o x WHERE x.user_id = a.user_id AND x.event_type = 'error' AND x.k > a.k AND x.k < b.k)",
    "K19_exits": "SELECT user_id, event_id, event_type <> 'error' AS persisting FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id DESC) AS k FROM events) WHERE k = 1",
    "M15_validated_share": f"WITH {_matches_sql()}, v AS (SELECT item_id, bool_or(doc_id IN (SELECT doc_id FROM labels WHERE quality = 0)) AS v FROM m GROUP BY item_id) SELECT count(*) AS candidates, count(*) FILTER (v) AS validated, round(count(*) FILTER (v) / nullif(count(*), 0), 6) AS share FROM v",
    "S27_candidate_codes": f"WITH {_matches_sql()}, j AS (SELECT doc_id, h, n_after > 0 AND deployed > m.posted AS d, first_unit > m.posted AS s FROM m JOIN k USING (item_id)) SELECT 'all' AS class, count(DISTINCT doc_id) AS units, count(DISTINCT h) AS codes FROM j UNION ALL SELECT 'disseminator', count(DISTINCT doc_id), count(DISTINCT h) FROM j WHERE d UNION ALL SELECT 'source', count(DISTINCT doc_id), count(DISTINCT h) FROM j WHERE s",
}
