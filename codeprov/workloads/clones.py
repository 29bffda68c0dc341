"""Clone search workloads over prose: ``benchmark`` items are the snippets, ``documents`` the units."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.baselines import bruteforce, embedding, exact, ordered
from codeprov.clone import candidates, fingerprint, links, match
from codeprov.clone.fuzzyhash import ALPHABET
from codeprov.clone.normalise import strip_layout
from codeprov.clone.score import delta, order_free
from codeprov.measure import confusion, cost, sweep
from codeprov.operators.joins import broadcast_blocks
from codeprov.session import cut_lineage, table


def _items(spark, sf):
    return cut_lineage(fingerprint.build(table(spark, sf, "benchmark"), "item_id"))


def _documents(spark, sf):
    """Fingerprints of all documents, written once: candidates, counts and scores read them again."""
    return cut_lineage(_prints(spark, sf))


def _prints(spark, sf):
    return fingerprint.build(table(spark, sf, "documents"), "doc_id")


def _named(pairs: DataFrame, *columns: str) -> DataFrame:
    out = pairs.withColumnsRenamed({"query_id": "item_id", "target_id": "doc_id"})
    return out.withColumns({c: F.round(c, 6) for c in ("score", "containment") if c in out.columns}).withColumns({c: F.col(c).cast("long") for c in ("shared", "n_grams") if c in out.columns}).select(*columns)


def w01(spark, sf):
    return _named(match.find_clones(_items(spark, sf), _documents(spark, sf)), "item_id", "doc_id", "shared", "n_grams", "score")


def w02(spark, sf):
    return _named(match.find_clones(_items(spark, sf), _documents(spark, sf), match.CONSERVATIVE), "item_id", "doc_id", "shared", "n_grams", "score")


def w03(spark, sf):
    return _named(candidates.retrieve(_items(spark, sf), _documents(spark, sf)), "item_id", "doc_id", "shared", "n_grams", "containment")


def w04(spark, sf):
    items, docs = fingerprint.build(table(spark, sf, "benchmark"), "item_id"), fingerprint.build(table(spark, sf, "documents"), "doc_id")
    both = items.withColumn("kind", F.lit("item")).unionByName(docs.withColumn("kind", F.lit("document")))
    return both.select("kind", "id", "fp", F.col("n_subs").cast("long").alias("n_parts"), F.col("len").cast("long").alias("fp_len"))


def w05(spark, sf):
    names = table(spark, sf, "nation").select("n_name").unionByName(table(spark, sf, "region").select(F.col("r_name").alias("n_name")))
    a, b = names.select(F.col("n_name").alias("a")), names.select(F.col("n_name").alias("b"))
    return a.crossJoin(F.broadcast(b)).select("a", "b", F.levenshtein("a", "b").cast("long").alias("dist"), F.round(delta("a", "b"), 6).alias("delta"))


def w06(spark, sf):
    """Each document with its class of equal fingerprints and the number of its clones among all others."""
    return links.self_links(_prints(spark, sf)).withColumnRenamed("id", "doc_id")


def _contained(spark, sf):
    items = table(spark, sf, "benchmark").where("text IS NOT NULL AND text <> ''").select(F.col("item_id").alias("query_id"), F.col("text").alias("needle"))
    docs = table(spark, sf, "documents").select(F.col("doc_id").alias("target_id"), "text")
    found = [docs.join(block, F.contains("text", "needle")) for block in broadcast_blocks(items, "16 + length(needle)")]
    return reduce(DataFrame.unionByName, found).select("query_id", "target_id")


NS, ETAS, EPSS = [2, 3, 4, 5], [0.3, 0.5, 0.7], [0.5, 0.6, 0.7, 0.8, 0.9]


def w07(spark, sf):
    return sweep.sweep(_items(spark, sf), _documents(spark, sf), _contained(spark, sf), NS, ETAS, EPSS)


def w09(spark, sf):
    return embedding.cosine_counts(table(spark, sf, "embeddings"), [0.2, 0.3, 0.4, 0.9])


def w10(spark, sf):
    """Scores of every item against all documents."""
    docs = fingerprint.build(table(spark, sf, "documents"), "doc_id")
    return _named(bruteforce.all_pairs(_items(spark, sf), docs), "item_id", "doc_id", "score")


def w11(spark, sf):
    p = _documents(spark, sf).withColumn("r", F.reverse("subs"))
    return p.where("n_subs > 0").select(F.col("id").alias("doc_id"), F.round(order_free("subs", "r"), 6).alias("order_free"), F.round(ordered.whole_score("fp", F.array_join("r", ".")), 6).alias("whole"))


def w12(spark, sf):
    docs = table(spark, sf, "documents").where("text IS NOT NULL")
    kinds = [("exact", docs, F.col("text")), ("layout", docs, strip_layout("text")), ("canonical", _documents(spark, sf), F.col("fp"))]
    return reduce(DataFrame.unionByName, [exact.groups(d, k).select(F.lit(name).alias("kind"), "groups", "rows", "surplus") for name, d, k in kinds])


def w31(spark, sf):
    q, t = _items(spark, sf), _documents(spark, sf)
    rows = []
    for n in (2, 3, 4):
        for eta in (0.3, 0.5, 0.7):
            rows.append(cost.reduction(candidates.retrieve(q, t, n, eta), q, t).select(F.lit(n).cast("long").alias("n"), F.lit(eta).alias("eta"), "all_pairs", "candidates", "comparisons", "ratio"))
    return reduce(DataFrame.unionByName, rows)


def w32(spark, sf):
    """Documents that have a clone among the others, as a detector of low quality."""
    labels = table(spark, sf, "labels")
    asked = labels.select(F.col("doc_id").alias("id")).distinct()
    hits = links.has_link(_prints(spark, sf), asked).select(F.col("id").alias("doc_id"), F.lit(1).alias("hit"))
    labels = labels.join(hits, "doc_id", "left")
    counts = labels.agg(F.count_if((F.col("hit") == 1) & (F.col("quality") == 0)).alias("tp"), F.count_if((F.col("hit") == 1) & (F.col("quality") == 1)).alias("fp"), F.count_if(F.col("quality") == 0).alias("labels"))
    return confusion.rates(counts).select("prec", "rec", "f1")


def strategies(spark, sf):
    """Candidates by each exact strategy, which must agree, and the share that the hashed one finds."""
    q, t = _items(spark, sf), _documents(spark, sf)
    plain = candidates.retrieve(q, t, strategy="plain").select("query_id", "target_id")
    out = []
    for name in ("plain", "prefix"):
        got = candidates.retrieve(q, t, strategy=name).select("query_id", "target_id")
        both = got.join(plain, ["query_id", "target_id"], "left_semi")
        out.append(both.agg(F.lit(name).alias("strategy"), F.count("*").alias("found")))
    return reduce(DataFrame.unionByName, out)


_PART = r"[.!?\n]+"
_WORD = r"[^\p{L}\p{N}]+"


def prints(name: str, source: str, id: str) -> str:
    letter = f"substr('{ALPHABET}', CAST('0x' || substr(md5(t), 1, 4) AS INT) % 64 + 1, 1)"
    part = f"array_to_string(list_transform(list_filter(regexp_split_to_array(p, '{_WORD}'), lambda t: t <> ''), lambda t: {letter}), '')"
    return f"{name} AS (SELECT {id} AS id, list_filter(list_transform(regexp_split_to_array(lower(coalesce(text, '')), '{_PART}'), lambda p: {part}), lambda s: s <> '') AS subs FROM {source})"


def grams(name: str, source: str, n: int) -> str:
    """A fingerprint whose parts are all shorter than ``n`` has its whole string as its only gram."""
    short = f"len(list_filter(subs, lambda s: length(s) >= {n})) = 0 AND len(subs) > 0"
    return f"{name} AS (SELECT id, unnest(CASE WHEN {short} THEN [array_to_string(subs, '.')] ELSE list_distinct(flatten(list_transform(list_filter(subs, lambda s: length(s) >= {n}), lambda s: list_transform(range(1, length(s) - {n} + 2), lambda i: substr(s, i::INT, {n}))))) END) AS gram FROM {source})"


def shared(name: str, q: str, t: str, eta: float, where: str = "true") -> str:
    return f"""{name} AS (SELECT query_id, target_id, shared, n_grams FROM (SELECT a.id AS query_id, b.id AS target_id, count(*) AS shared FROM {q} a JOIN {t} b USING (gram) WHERE {where} GROUP BY ALL)
      JOIN (SELECT id AS query_id, count(*) AS n_grams FROM {q} GROUP BY ALL) USING (query_id) WHERE shared >= {eta} * n_grams)"""


def scores(name: str, pairs: str, q: str, t: str) -> str:
    return f"""{name} AS (SELECT query_id, target_id, avg(best) AS score FROM (SELECT query_id, target_id, k, max(100.0 * (1 - levenshtein(s, u) / greatest(length(s), length(u)))) AS best
      FROM (SELECT {pairs}.*, unnest(range(len(q.subs))) AS k, q.subs AS qs, t.subs AS ts FROM {pairs} JOIN {q} q ON q.id = query_id JOIN {t} t ON t.id = target_id) x,
      LATERAL (SELECT qs[k + 1] AS s, unnest(ts) AS u) GROUP BY ALL) GROUP BY ALL)"""


def _search(eps: float) -> str:
    return f"""WITH {prints('q', 'benchmark', 'item_id')}, {prints('t', 'documents', 'doc_id')}, {grams('qg', 'q', 3)}, {grams('tg', 't', 3)}, {shared('c', 'qg', 'tg', 0.5)}, {scores('s', 'c', 'q', 't')}
SELECT query_id AS item_id, target_id AS doc_id, shared, n_grams, round(score, 6) AS score FROM c JOIN s USING (query_id, target_id) WHERE score >= {100 * eps}"""


_SELF = f"""{prints('t', 'documents', 'doc_id')}, {grams('g', 't', 3)}, {shared('c', 'g', 'g', 0.5, 'a.id <> b.id')}, {scores('s', 'c', 't', 't')}"""


def _sweep() -> str:
    head = [prints("q", "benchmark", "item_id"), prints("t", "documents", "doc_id"), "truth AS (SELECT item_id AS query_id, doc_id AS target_id FROM benchmark b JOIN documents d ON contains(d.text, b.text) WHERE b.text <> '')"]
    found = []
    for n in NS:
        head += [grams(f"qg{n}", "q", n), grams(f"tg{n}", "t", n), shared(f"c{n}", f"qg{n}", f"tg{n}", min(ETAS)), scores(f"s{n}", f"c{n}", "q", "t")]
        found.append(f"SELECT {n} AS n, query_id, target_id, shared, n_grams, score FROM c{n} JOIN s{n} USING (query_id, target_id)")
    head.append(f"found AS (SELECT f.*, truth.query_id IS NOT NULL AS hit FROM ({' UNION ALL '.join(found)}) f LEFT JOIN truth USING (query_id, target_id))")
    grid = f"(SELECT unnest({NS}) AS n), (SELECT unnest({ETAS}::DOUBLE[]) AS eta), (SELECT unnest({EPSS}::DOUBLE[]) AS eps)"
    head.append(f"k AS (SELECT g.n, g.eta, g.eps, count(*) FILTER (shared >= g.eta * n_grams AND score >= 100 * g.eps - 1e-9 AND hit) AS tp, count(*) FILTER (shared >= g.eta * n_grams AND score >= 100 * g.eps - 1e-9 AND NOT hit) AS fp FROM (SELECT * FROM {grid}) g LEFT JOIN found USING (n) GROUP BY ALL)")
    return f"""WITH {', '.join(head)}
SELECT n::BIGINT AS n, eta, eps, tp, fp, l - tp AS fn, round(tp / nullif(tp + fp, 0), 6) AS prec, round(tp / nullif(l, 0), 6) AS rec, round(2 * (tp / nullif(tp + fp, 0)) * (tp / nullif(l, 0)) / nullif(tp / nullif(tp + fp, 0) + tp / nullif(l, 0), 0), 6) AS f1 FROM k, (SELECT count(*) AS l FROM truth)"""


def _reduction() -> str:
    head, rows = [prints("q", "benchmark", "item_id"), prints("t", "documents", "doc_id")], []
    for n in (2, 3, 4):
        head += [grams(f"qg{n}", "q", n), grams(f"tg{n}", "t", n), shared(f"c{n}", f"qg{n}", f"tg{n}", 0.3)]
        for eta in (0.3, 0.5, 0.7):
            rows.append(f"SELECT {n}::BIGINT AS n, {eta}::DOUBLE AS eta, (SELECT count(*) FROM q) * (SELECT count(*) FROM t) AS all_pairs, count(*) AS candidates, coalesce(sum(len(q.subs) * len(t.subs)), 0)::BIGINT AS comparisons FROM c{n} JOIN q ON q.id = query_id JOIN t ON t.id = target_id WHERE shared >= {eta} * n_grams")
    return f"WITH {', '.join(head)} SELECT *, round(candidates / all_pairs, 6) AS ratio FROM ({' UNION ALL '.join(rows)})"


QUERIES = {
    "W01_clone_search": w01,
    "W02_clone_search_conservative": w02,
    "W03_candidates": w03,
    "W04_fingerprints": w04,
    "W05_delta_pairs": w05,
    "W06_self_clones": w06,
    "W07_sweep": w07,
    "W09_embedding_baseline": w09,
    "W10_bruteforce_scores": w10,
    "W11_order_swap": w11,
    "W12_exact_and_layout_dups": w12,
    "W31_cost": w31,
    "W32_labelled_docs": w32,
    "W03_strategies": strategies,
}
SQL = {
    "W01_clone_search": _search(0.7),
    "W02_clone_search_conservative": _search(0.9),
    "W03_candidates": f"WITH {prints('q', 'benchmark', 'item_id')}, {prints('t', 'documents', 'doc_id')}, {grams('qg', 'q', 3)}, {grams('tg', 't', 3)}, {shared('c', 'qg', 'tg', 0.5)} SELECT query_id AS item_id, target_id AS doc_id, shared, n_grams, round(shared / n_grams, 6) AS containment FROM c",
    "W04_fingerprints": f"WITH {prints('q', 'benchmark', 'item_id')}, {prints('t', 'documents', 'doc_id')} SELECT kind, id, array_to_string(subs, '.') AS fp, len(subs)::BIGINT AS n_parts, length(array_to_string(subs, '.'))::BIGINT AS fp_len FROM (SELECT 'item' AS kind, * FROM q UNION ALL SELECT 'document', * FROM t)",
    "W05_delta_pairs": "WITH n AS (SELECT n_name AS x FROM nation UNION ALL SELECT r_name FROM region) SELECT a.x AS a, b.x AS b, levenshtein(a.x, b.x)::BIGINT AS dist, round(100.0 * (1 - levenshtein(a.x, b.x) / greatest(length(a.x), length(b.x))), 6) AS delta FROM n a, n b",
    "W06_self_clones": f"WITH {_SELF}, l AS (SELECT query_id AS id, count(*) AS n FROM s WHERE score >= 70 GROUP BY ALL) SELECT id AS doc_id, CASE WHEN len(subs) = 0 THEN id ELSE min(id) OVER (PARTITION BY array_to_string(subs, '.')) END AS class_id, coalesce(n, 0)::BIGINT AS n_links FROM t LEFT JOIN l USING (id)",
    "W07_sweep": _sweep(),
    "W09_embedding_baseline": "WITH p AS (SELECT a.label AS la, b.label AS lb, list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) AS c FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id) SELECT threshold, count(c) AS pairs, count(*) FILTER (la = lb) AS same_label FROM (SELECT unnest([0.2, 0.3, 0.4, 0.9]::DOUBLE[]) AS threshold) LEFT JOIN p ON c >= threshold GROUP BY ALL",
    "W10_bruteforce_scores": f"WITH {prints('q', 'benchmark', 'item_id')}, {prints('t', 'documents', 'doc_id')}, c AS (SELECT q.id AS query_id, t.id AS target_id FROM q, t), {scores('s', 'c', 'q', 't')} SELECT q.id AS item_id, t.id AS doc_id, round(coalesce(score, CASE WHEN len(q.subs) > 0 THEN 0.0 END), 6) AS score FROM q CROSS JOIN t LEFT JOIN s ON s.query_id = q.id AND s.target_id = t.id",
    "W11_order_swap": f"WITH {prints('t', 'documents', 'doc_id')} SELECT id AS doc_id, 100.0::DOUBLE AS order_free, round(100.0 * (1 - levenshtein(array_to_string(subs, '.'), array_to_string(list_reverse(subs), '.')) / length(array_to_string(subs, '.'))), 6) AS whole FROM t WHERE len(subs) > 0",
    "W12_exact_and_layout_dups": f"WITH {prints('t', 'documents', 'doc_id')}, k AS (SELECT 'exact' AS kind, text AS x FROM documents WHERE text IS NOT NULL UNION ALL SELECT 'layout', trim(regexp_replace(lower(text), '\\s+', ' ', 'g')) FROM documents WHERE text IS NOT NULL UNION ALL SELECT 'canonical', array_to_string(subs, '.') FROM t) SELECT kind, count(*) AS groups, sum(n)::BIGINT AS rows, sum(n - 1)::BIGINT AS surplus FROM (SELECT kind, x, count(*) AS n FROM k GROUP BY ALL) GROUP BY ALL",
    "W31_cost": _reduction(),
    "W32_labelled_docs": f"WITH {_SELF}, h AS (SELECT DISTINCT query_id AS doc_id FROM s WHERE score >= 70), k AS (SELECT count(*) FILTER (h.doc_id IS NOT NULL AND quality = 0) AS tp, count(*) FILTER (h.doc_id IS NOT NULL AND quality = 1) AS fp, count(*) FILTER (quality = 0) AS l FROM labels LEFT JOIN h USING (doc_id)) SELECT round(tp / nullif(tp + fp, 0), 6) AS prec, round(tp / nullif(l, 0), 6) AS rec, round(2 * (tp / nullif(tp + fp, 0)) * (tp / nullif(l, 0)) / nullif(tp / nullif(tp + fp, 0) + tp / nullif(l, 0), 0), 6) AS f1 FROM k",
    "W03_strategies": f"WITH {prints('q', 'benchmark', 'item_id')}, {prints('t', 'documents', 'doc_id')}, {grams('qg', 'q', 3)}, {grams('tg', 't', 3)}, {shared('c', 'qg', 'tg', 0.5)} SELECT unnest(['plain', 'prefix']) AS strategy, (SELECT count(*) FROM c) AS found",
}
