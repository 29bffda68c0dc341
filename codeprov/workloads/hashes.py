"""Clone search by each fuzzy hash, what one changed character does to each, and how well each finds what is there."""

from __future__ import annotations

from functools import partial, reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.baselines import ordered
from codeprov.clone import fingerprint, match
from codeprov.clone.fuzzyhash import ALPHABET, FNV_OFFSET, FNV_PRIME, LEAST_BLOCK, VARIANTS, WINDOW
from codeprov.measure.confusion import rates
from codeprov.session import cut_lineage, table
from codeprov.workloads import clones


def _sides(spark, sf, variant):
    return tuple(cut_lineage(fingerprint.build(table(spark, sf, name), id, variant=variant)) for name, id in (("benchmark", "item_id"), ("documents", "doc_id")))


def search(variant, spark, sf):
    return clones._named(match.find_clones(*_sides(spark, sf, variant)), "item_id", "doc_id", "shared", "n_grams", "score")


def changed_character(spark, sf):
    """Letters of each document's fingerprint that change with the character in its middle (a ``q`` in its place).

    They are counted on the parts that only one of the two has, so that the distance is linear in long texts.
    """
    docs = table(spark, sf, "documents").where("length(text) > 0").select("doc_id", "text")
    edited = docs.withColumn("text", F.expr("concat(substr(text, 1, length(text) div 2), 'q', substr(text, length(text) div 2 + 2))"))
    rows = []
    for v in VARIANTS:
        a, b = (fingerprint.build(d, "doc_id", variant=v).select(F.col("id").alias("doc_id"), F.col("subs").alias(name), "len") for d, name in ((docs, "before"), (edited, "after")))
        only = [F.array_join(F.array_except(x, y), ".") for x, y in (("before", "after"), ("after", "before"))]
        both = a.join(b.drop("len"), "doc_id")
        rows.append(both.select(F.lit(v).alias("variant"), "doc_id", F.col("len").cast("long").alias("letters"), F.levenshtein(*only).cast("long").alias("changed")))
    return reduce(DataFrame.unionByName, rows)


def match_quality(spark, sf):
    """Pairs at 70 points by hash and by score, held against the pairs whose document contains the item's text."""
    truth = cut_lineage(clones._contained(spark, sf)).withColumn("hit", F.lit(1))
    labels = truth.agg(F.count("*").alias("labels"))
    rows = []
    for v in VARIANTS:
        q, t = _sides(spark, sf, v)
        pairs = match.scored(q, t).join(q.select(F.col("id").alias("query_id"), F.col("fp").alias("qf")), "query_id").join(t.select(F.col("id").alias("target_id"), F.col("fp").alias("tf")), "target_id")
        pairs = pairs.select("query_id", "target_id", "score", ordered.whole_score("qf", "tf").alias("whole"), (F.col("qf") == F.col("tf")).alias("same"))
        pairs = pairs.join(truth, ["query_id", "target_id"], "left")
        kinds = {"order-free": F.col("score") >= 70, "whole string": F.col("whole") >= 70, "equal": F.col("same")}
        counted = pairs.agg(*(F.count_if(kept & (F.col("hit").isNotNull() if of else F.col("hit").isNull())).alias(f"{kind}.{of:d}") for kind, kept in kinds.items() for of in (True, False)))
        tall = counted.select(F.inline(F.array(*(F.struct(F.lit(kind).alias("rival"), F.col(f"`{kind}.1`").alias("tp"), F.col(f"`{kind}.0`").alias("fp")) for kind in kinds))))
        rows.append(tall.withColumn("variant", F.lit(v)))
    return rates(reduce(DataFrame.unionByName, rows).join(F.broadcast(labels))).select("variant", "rival", "tp", "fp", "prec", "rec", "f1")


def unit_fingerprints(spark, sf):
    docs = fingerprint.build(table(spark, sf, "documents"), "doc_id", units=True)
    return docs.select(F.col("id").alias("doc_id"), F.col("n_units").cast("long").alias("n_units"), "fp")


def _letters(name: str, source: str, variant: str) -> str:
    """Letters of the distinct words ``t`` of ``source``, from sums over the last bytes in place of a running state."""
    at = lambda j: f"coalesce(lag(b, {j}) OVER w, 0)" if j else "b"
    plain = " + ".join(f"{WINDOW - j + 1} * {at(j)}" for j in range(WINDOW))
    turned = reduce(lambda x, y: f"xor({x}, {y})", (f"(({at(j)} * {1 << 5 * j}) & 4294967295)" for j in range(WINDOW)))
    hit = f"({plain} + {turned}) % 4294967296 % {LEAST_BLOCK} = {LEAST_BLOCK - 1}"
    piece = f"i // {WINDOW}" if variant == "fixed7" else "coalesce(sum(hit::INT) OVER (PARTITION BY t ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)"
    return f"""{name}_b AS (SELECT t, unnest(range(octet_length(encode(t)))) AS i, ('0x' || unnest(regexp_extract_all(hex(encode(t)), '..')))::BIGINT AS b FROM (SELECT DISTINCT t FROM {source})),
      {name}_h AS (SELECT t, i, b, {hit} AS hit FROM {name}_b WINDOW w AS (PARTITION BY t ORDER BY i)),
      {name}_p AS (SELECT t, {piece} AS piece, i, b FROM {name}_h),
      {name}_l AS (SELECT t, piece, list_reduce([{FNV_OFFSET}::BIGINT] || list(b ORDER BY i), lambda h, x: xor(h * {FNV_PRIME}, x) & 4294967295) AS h FROM {name}_p GROUP BY t, piece),
      {name} AS (SELECT t, string_agg(substr('{ALPHABET}', (h & 63)::INT + 1, 1), '' ORDER BY piece) AS s FROM {name}_l GROUP BY t)"""


def prints(name: str, source: str, id: str, variant: str) -> str:
    """The fingerprint tables of ``clones.prints`` for any hash; ids stay where no part is left."""
    if variant == "token64":
        return clones.prints(name, source, id)
    return f"""{name}_s AS (SELECT id, p, unnest(range(len(ws))) AS i, unnest(ws) AS t FROM (SELECT id, p, list_filter(regexp_split_to_array(part, '{clones._WORD}'), lambda x: x <> '') AS ws
        FROM (SELECT id, unnest(range(len(ps))) AS p, unnest(ps) AS part FROM (SELECT {id} AS id, regexp_split_to_array(lower(coalesce(text, '')), '{clones._PART}') AS ps FROM {source})))),
      {_letters(f'{name}_w', f'{name}_s', variant)},
      {name}_j AS (SELECT id, p, string_agg(s, '' ORDER BY i) AS sub FROM {name}_s JOIN {name}_w USING (t) GROUP BY id, p),
      {name} AS (SELECT {id} AS id, coalesce(subs, []) AS subs FROM {source} LEFT JOIN (SELECT id AS j, list(sub ORDER BY p) AS subs FROM {name}_j GROUP BY id) ON j = {id})"""


def _found(variant: str, tag: str = "") -> str:
    q, t, c, s = (f"{x}{tag}" for x in "qtcs")
    return f"{prints(q, 'benchmark', 'item_id', variant)}, {prints(t, 'documents', 'doc_id', variant)}, {clones.grams(q + 'g', q, 3)}, {clones.grams(t + 'g', t, 3)}, {clones.shared(c, q + 'g', t + 'g', 0.5)}, {clones.scores(s, c, q, t)}"


def _search(variant: str) -> str:
    return f"WITH {_found(variant)} SELECT query_id AS item_id, target_id AS doc_id, shared, n_grams, round(score, 6) AS score FROM c JOIN s USING (query_id, target_id) WHERE score >= 70"


def _changed() -> str:
    head = ["o AS (SELECT doc_id, text FROM documents WHERE length(text) > 0)", "e AS (SELECT doc_id, substr(text, 1, length(text) // 2) || 'q' || substr(text, length(text) // 2 + 2) AS text FROM o)"]
    rows = []
    for v in VARIANTS:
        head += [prints(f"a_{v}", "o", "doc_id", v), prints(f"b_{v}", "e", "doc_id", v)]
        rows.append(f"SELECT '{v}' AS variant, id AS doc_id, a.subs AS x, b.subs AS y FROM a_{v} a JOIN b_{v} b USING (id)")
    only = [f"array_to_string(list_filter({x}, lambda p, i: NOT list_contains({y}, p) AND list_position({x}, p) = i), '.')" for x, y in ("xy", "yx")]
    return f"WITH {', '.join(head)} SELECT variant, doc_id, length(array_to_string(x, '.'))::BIGINT AS letters, levenshtein({', '.join(only)})::BIGINT AS changed FROM ({' UNION ALL '.join(rows)})"


def _quality() -> str:
    head, rows = ["truth AS (SELECT item_id AS query_id, doc_id AS target_id FROM benchmark b JOIN documents d ON contains(d.text, b.text) WHERE b.text <> '')"], []
    for v in VARIANTS:
        tag = f"_{v}"
        head.append(_found(v, tag))
        pairs = f"SELECT query_id, target_id, score, array_to_string(q.subs, '.') AS x, array_to_string(t.subs, '.') AS y FROM s{tag} JOIN q{tag} q ON q.id = query_id JOIN t{tag} t ON t.id = target_id"
        rows.append(f"SELECT '{v}' AS variant, p.*, truth.query_id IS NOT NULL AS hit FROM ({pairs}) p LEFT JOIN truth USING (query_id, target_id)")
    head.append(f"p AS ({' UNION ALL '.join(rows)})")
    kinds = {"order-free": "score >= 70", "whole string": "100.0 * (1 - levenshtein(x, y) / greatest(length(x), length(y))) >= 70", "equal": "x = y"}
    each = " UNION ALL ".join(f"SELECT v AS variant, '{k}' AS rival, count(*) FILTER (hit AND {c}) AS tp, count(*) FILTER (NOT hit AND {c}) AS fp FROM (SELECT unnest({list(VARIANTS)}) AS v) LEFT JOIN p ON variant = v GROUP BY v" for k, c in kinds.items())
    prec, rec = "tp / nullif(tp + fp, 0)", "tp / nullif(l, 0)"
    return f"WITH {', '.join(head)} SELECT variant, rival, tp, fp, round({prec}, 6) AS prec, round({rec}, 6) AS rec, round(2 * ({prec}) * ({rec}) / nullif({prec} + {rec}, 0), 6) AS f1 FROM ({each}), (SELECT count(*) AS l FROM truth)"


def lengths() -> str:
    """Lengths of the items' fingerprints by each hash, and of the piecewise hash of their undivided texts."""
    head = [*(prints(f"q_{v}", "benchmark", "item_id", v) for v in VARIANTS), "u AS (SELECT item_id, coalesce(text, '') AS t FROM benchmark)", _letters("w", "u", "ctph")]
    rows = [f"SELECT '{v}' AS variant, id AS item_id, length(array_to_string(subs, '.'))::BIGINT AS len FROM q_{v}" for v in VARIANTS]
    rows.append("SELECT 'whole text', item_id, coalesce(length(s), 0)::BIGINT FROM u LEFT JOIN w USING (t)")
    return f"WITH {', '.join(head)} {' UNION ALL '.join(rows)}"


def _units() -> str:
    lines = "SELECT doc_id || ':' || u AS id, doc_id, u, line AS text FROM (SELECT doc_id, unnest(range(len(ls))) AS u, unnest(ls) AS line FROM (SELECT doc_id, regexp_split_to_array(coalesce(text, ''), '\\n+') AS ls FROM documents))"
    return f"""WITH l AS ({lines}), {clones.prints('t', 'l', 'id')}, k AS (SELECT doc_id, u, array_to_string(subs, '.') AS fp FROM t JOIN l USING (id) WHERE len(subs) > 0)
SELECT documents.doc_id, count(u) AS n_units, coalesce(string_agg(fp, ':' ORDER BY u), '') AS fp FROM documents LEFT JOIN k USING (doc_id) GROUP BY documents.doc_id"""


QUERIES = {
    "W34_clones_ctph": partial(search, "ctph"),
    "W35_clones_fixed7": partial(search, "fixed7"),
    "C7_changed_character": changed_character,
    "B17_match_quality": match_quality,
    "C8_unit_fingerprints": unit_fingerprints,
}
SQL = {
    "W34_clones_ctph": _search("ctph"),
    "W35_clones_fixed7": _search("fixed7"),
    "C7_changed_character": _changed(),
    "B17_match_quality": _quality(),
    "C8_unit_fingerprints": _units(),
}
