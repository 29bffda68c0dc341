"""Findings of round 2: each test failed before its change."""

import random

import numpy as np
import pytest
from codeprov.baselines import embedding, ordered
from codeprov.clone import fingerprint, links, match
from codeprov.clone.score import delta
from codeprov.corpus import derive
from codeprov.functions import text
from codeprov.graph import local
from codeprov.measure import confusion
from codeprov.queries import QUERIES
from codeprov.study import pipeline, review
from codeprov.study.source_profile import fingerprints
from pyspark.sql import functions as F

SF = "/root/testdata/sf0.001"


def test_f1_cosine_pairs_are_counted_where_they_are_formed(spark):
    plan = QUERIES["W09_embedding_baseline"](spark, SF)._jdf.queryExecution().optimizedPlan().toString()
    assert "cosine" not in plan
    g = np.random.default_rng(1)
    m = g.normal(size=(60, 4)).astype(np.float32)
    m[7], m[9] = 0, m[8]
    labels = [None if i % 11 == 0 else i % 3 for i in range(60)]
    df = spark.createDataFrame([(i, x.tolist(), l) for i, (x, l) in enumerate(zip(m, labels, strict=True))], "vec_id long, embedding array<float>, label int")
    unit = m.astype(float) / np.maximum(np.linalg.norm(m.astype(float), axis=1, keepdims=True), 1e-300)
    pairs = [(i, j) for i in range(60) for j in range(i + 1, 60) if 7 not in (i, j)]
    for block in (7, 8, 100):
        got = {r.threshold: (r.pairs, r.same_label) for r in embedding.cosine_counts(df, [0.2, 0.9, 1.5], block=block).collect()}
        hit = {t: [(i, j) for i, j in pairs if unit[i] @ unit[j] >= t] for t in got}
        assert got == {t: (len(h), sum(labels[i] is not None and labels[i] == labels[j] for i, j in h)) for t, h in hit.items()}
        assert {(r.a, r.b) for r in embedding.cosine_pairs(df, 0.9, block=block).collect()} == set(hit[0.9])


def test_f2_recursion_has_no_limit_of_rows(spark):
    key = "spark.sql.cteRecursionRowLimit"
    spark.conf.set(key, "100")
    try:
        rows = QUERIES["O_recursive"](spark, SF).collect()
    finally:
        spark.conf.unset(key)
    assert sum(r.depth for r in rows) > 100


@pytest.mark.parametrize("key", ["W26_functions_statements", "W25_rule_by_tool_table", "W27_parse_gain"])
def test_f3_f13_f14_equal_programs_are_read_once(spark, tmp_path, key):
    """Each part three times under other keys: counts grow in proportion, the texts that are read do not grow."""
    part = spark.read.parquet(f"{SF}/part.parquet").where("p_partkey < 40")
    part.write.parquet(f"{tmp_path}/a/part.parquet")
    part.crossJoin(spark.range(3)).withColumn("p_partkey", F.col("p_partkey") + 34 * 1000 * F.col("id")).drop("id").write.parquet(f"{tmp_path}/b/part.parquet")
    counts = ("labels", "tp", "fp", "strict_ok", "lenient_ok", "gain")
    a, b = ({tuple(r[c] for c in r.__fields__ if isinstance(r[c], str)): [r[c] for c in r.__fields__ if c in counts] for r in QUERIES[key](spark, f"{tmp_path}/{x}").collect()} for x in "ab")
    assert b == {k: [3 * x for x in v] for k, v in a.items()}
    small, large = (derive.kinds(spark.read.parquet(f"{tmp_path}/{x}/part.parquet")) for x in "ab")
    assert small.count() == large.count() and large.agg(F.sum("n")).first()[0] == 3 * small.agg(F.sum("n")).first()[0]


@pytest.fixture(scope="module")
def copies(spark, tmp_path_factory):
    """Sixty parts, each three times under keys of the same program."""
    at = str(tmp_path_factory.mktemp("copies"))
    part = spark.read.parquet(f"{SF}/part.parquet").where("p_partkey < 60")
    part.crossJoin(spark.range(3)).withColumn("p_partkey", F.col("p_partkey") + 34 * 1000 * F.col("id")).drop("id").write.parquet(f"{at}/part.parquet")
    return at


def test_f10_classes_of_copies_count_all_pairs(spark, copies):
    units = derive.units(spark.read.parquet(f"{copies}/part.parquet"))
    found = match.self_clones(fingerprints(units, "unit_id"))
    want = confusion.pairs(found, units.selectExpr("unit_id AS id", "rule_id AS class")).selectExpr("class", "tp", "fp", "labels AS same_pairs", "rec AS recall")
    got = QUERIES["W08_class_tp_fp"](spark, copies)
    assert sorted(got.collect()) == sorted(want.collect())
    assert match.collapse(fingerprints(units, "unit_id"))[0].count() * 3 <= units.count()


def test_f8_residue_of_copies(spark, copies):
    units = derive.units(spark.read.parquet(f"{copies}/part.parquet"))
    prints = fingerprints(units, "unit_id")
    good = prints.join(units.where("NOT weak AND mutation = 0").selectExpr("unit_id AS id"), "id", "left_semi")
    hit = match.find_clones(good, prints, match.Setting(3, 0.5, 0.9)).selectExpr("target_id AS unit_id")
    want = units.join(hit, "unit_id", "left_anti").groupBy("weak").count()
    assert sorted(QUERIES["S26_not_vetted"](spark, copies).collect()) == sorted(want.collect())
    assert "n" in derive.kinds(spark.read.parquet(f"{copies}/part.parquet")).columns


def test_f7_ablations_of_copies(spark, copies):
    units = derive.units(spark.read.parquet(f"{copies}/part.parquet")).where("mutation IN (0, 2)")
    got = {r.choice: r.pairs for r in QUERIES["B19_ablations"](spark, copies).collect()}
    for choice, options in (("canonical", {}), ("names kept", {"names": "keep"})):
        prints = fingerprints(units, "unit_id", **options)
        assert got[choice] == match.self_clones(prints, match.CONSERVATIVE).count() > 0
        assert match.class_clones(match.collapse(prints)[0], match.CONSERVATIVE).count() * 8 <= got[choice] + units.count() * 8


@pytest.mark.parametrize("key, table", [("O_scan_rows", "customer"), ("W08_published_totals", "labels"), ("W25_published_coverage", "labels")])
def test_f21_f26_f27_rows_come_from_a_table(spark, tmp_path, key, table):
    import os

    for t in ("customer", "documents", "labels"):
        if t != table:
            os.symlink(f"{SF}/{t}.parquet", tmp_path / f"{t}.parquet")
    spark.read.parquet(f"{SF}/{table}.parquet").limit(0).write.parquet(f"{tmp_path}/{table}.parquet")
    assert QUERIES[key](spark, str(tmp_path)).count() == 0 < QUERIES[key](spark, SF).count()


def test_f4_f5_study_parses_equal_texts_once(spark, copies):
    units = derive.units(spark.read.parquet(f"{copies}/part.parquet"))
    snippets = derive.snippets(spark.read.parquet(f"{SF}/benchmark.parquet")).withColumnRenamed("unit_id", "snippet_id")
    want = match.find_clones(fingerprints(snippets, "snippet_id"), fingerprints(units, "unit_id"), match.CONSERVATIVE).selectExpr("query_id", "target_id", "score")
    assert sorted(pipeline.map_clones(snippets, units).collect()) == sorted(want.collect())
    reps, members = pipeline._classes(units, "unit_id")
    assert members.count() == units.count() >= 3 * reps.count()


def test_f5_study_joins_units_to_texts_where_they_are_asked_for(spark, copies):
    part = spark.read.parquet(f"{copies}/part.parquet")
    deployed = F.when(F.col("id") % 13 != 0, F.col("id") * 37 % 71).alias("deployed_at")
    rows = derive.unit_rows(part).select("*", deployed)
    units = derive.units(part).join(rows.select(F.col("id").alias("unit_id"), "deployed_at"), "unit_id").select("unit_id", "code", "deployed_at")
    snippets = derive.snippets(spark.read.parquet(f"{SF}/benchmark.parquet")).select(F.col("unit_id").alias("snippet_id"), "code", (F.col("unit_id") % 7 * 10).alias("posted_at"))
    posted, times = ({r[0]: r[1] for r in d.collect()} for d in (snippets.select("snippet_id", "posted_at"), units.select("unit_id", "deployed_at")))
    pairs = [(r.snippet_id, r.unit_id) for r in pipeline.map_clones(snippets, units).collect()]
    broken = {r.snippet_id: set(r.rules) for r in pipeline.check_snippets(snippets).collect()}
    held = {(r.unit_id, r.rule_id) for r in local.evaluate_units(units).collect()}
    late = {(s, u) for s, u in pairs if s in broken and times[u] is not None and times[u] > posted[s]}
    early = {s for s, u in pairs if times[u] is not None and times[u] <= posted[s]}
    want = sorted((s, u, rule, s not in early) for s, u in late for rule in broken[s] if (u, rule) in held)
    programs, members = derive.shared(rows)
    for stages in (pipeline.run(snippets, units), pipeline.run(snippets, members, texts=programs.select(F.col("unit_id").alias("text_id"), "code"))):
        found = pipeline.later(stages["findings"], stages["units"])
        assert sorted((r.snippet_id, r.unit_id, r.rule_id, r.is_source) for r in found.collect()) == want != []
        assert {x[3] for x in want} == {True, False} and stages["matches"].count() * 3 <= len(pairs)
        n = {r.step: (r.disseminator, r.source_only) for r in pipeline.funnel(stages, snippets).collect()}
        assert n["candidate units"] == tuple(len({u for s, u in late if s not in early or not only}) for only in (False, True))
        assert n["validated units"] == tuple(len({x[1] for x in want if x[3] or not only}) for only in (False, True))
    assert programs.count() * 3 == units.count()


def test_f5_sample_is_the_same_in_any_order_of_rows(spark):
    rows = [(s, u, rule, rule[:1]) for s in range(6) for u in range(40, 46) for rule in ("a1", "b1", "c1")]
    one, two = (sorted(map(tuple, review.sample(spark.createDataFrame(x, "snippet_id long, unit_id long, rule_id string, category string").coalesce(1), 5).collect())) for x in (rows, rows[::-1]))
    assert one == two != [] and {r[2] for r in one} == {"a1"}


def test_f12_distances_of_long_strings(spark):
    g = random.Random(5)
    words = ["", "a", "ab", "ba"] + ["".join(g.choices("abcd", k=g.randint(1, 90))) for _ in range(40)]
    for a, b in zip(words, reversed(words), strict=True):
        assert text.levenshtein_bits(a, b) == text.levenshtein(a, b)
    a, b = ("".join(g.choices("abcdefgh", k=ordered.LONG + d)) for d in (5, 900))
    df = spark.createDataFrame([(a, b), (b, a), (a, a), ("abc", "abd"), (None, "a")], "a string, b string")
    got = df.select(ordered.whole_score("a", "b").alias("x"), delta("a", "b").alias("y")).collect()
    assert [r.x for r in got] == [r.y for r in got]
    plan = df.select(ordered.whole_score("a", "b"))._jdf.queryExecution().executedPlan().toString()
    assert "ArrowEvalPython" in plan


def _prints(spark, texts):
    return fingerprint.build(spark.createDataFrame(list(enumerate(texts)), "id long, text string"), "id")


@pytest.fixture(scope="module")
def near_texts():
    """Copies, copies with other words, texts of few letters, short and wordless ones."""
    g = random.Random(11)
    words = ["".join(g.choices("abcdefghij", k=4)) for _ in range(60)]
    texts = [None, "", "!", "ab", "ab", "a. b", "a. b", " ".join(words[:2])]
    for _ in range(25):
        parts = [" ".join(g.choices(words[:30], k=g.choice((1, 2, 4, 9, 14)))) for _ in range(g.randint(1, 7))]
        texts += [". ".join(parts)] * g.randint(1, 3)
        for _ in range(4):
            texts.append(". ".join(" ".join(w if g.random() < 0.85 else g.choice(words) for w in p.split()) for p in g.sample(parts, len(parts))))
    return texts


@pytest.mark.parametrize("setting", [match.Setting(), match.Setting(2, 0.3, 0.5), match.CONSERVATIVE])
def test_f6_f15_links_without_pairs(spark, near_texts, setting, monkeypatch):
    prints = _prints(spark, near_texts).cache()
    want = {}
    for r in match.self_clones(prints, setting).collect():
        want[r.query_id] = want.get(r.query_id, 0) + 1
    fps = {r.id: r.fp for r in prints.collect()}
    least = {fp: min(i for i in fps if fps[i] == fp) for fp in fps.values()}
    assert sum(want.values()) > 2 * len(want) > 40
    for letters in (1 << 20, 400):
        got = {r.id: (r.class_id, r.n_links) for r in links.self_links(prints, setting, letters).collect()}
        assert got == {i: (least[fp] if fp else i, want.get(i, 0)) for i, fp in fps.items()}
    plan = links.self_links(prints, setting)._jdf.queryExecution().optimizedPlan().toString()
    assert "target_id" not in plan and "levenshtein" not in plan


def test_f6_bounds_hold(spark, near_texts):
    fps = [r.fp for r in _prints(spark, near_texts).collect() if r.fp]
    a = links.Parts("".join(f"{fp}\n" for fp in fps).encode())
    links.numbered(a, a)
    every = np.arange(len(a.length))
    high = links.bounds(a, every[:40], a, every)
    for i in range(40):
        true = [text.delta(a[i].decode(), a[j].decode()) for j in every]
        assert all(x <= 100 * h + 1e-3 and (h == 1) == (a[i] == a[j]) for x, h, j in zip(true, high[i], every, strict=True))
        assert links.best(a, i, a, every[60:], high[i, 60:]) == max(true[60:])


@pytest.mark.parametrize("setting", [match.Setting(), match.Setting(2, 0.3, 0.5), match.CONSERVATIVE])
def test_f15_only_labelled_documents_are_searched_for(spark, near_texts, setting, monkeypatch):
    prints = _prints(spark, near_texts).cache()
    linked = {r.query_id for r in match.self_clones(prints, setting).collect()}
    asked = spark.createDataFrame([(i,) for i in range(0, len(near_texts) + 9, 2)], "id long")
    for letters in (1 << 20, 400):
        got = [r.id for r in links.has_link(prints, asked, setting, letters).collect()]
        assert sorted(got) == sorted(i for i in linked if i % 2 == 0)
    monkeypatch.delattr(links, "self_links")
    assert QUERIES["W32_labelled_docs"](spark, SF).count() == 1


def test_f9_sweep_scores_each_pair_once(spark, near_texts, monkeypatch):
    from codeprov.clone import levels
    from codeprov.measure import sweep

    g = random.Random(3)
    ab = "".join(g.choices("abcdefgh", k=64))
    words = ["a", "ab", ab, ab[:63], ab + "abcdefgh"] + ["".join(g.choices("abcdefgh", k=g.randint(1, 70))) for _ in range(40)]
    parts = levels._parts([".".join(words)])
    for s in words:
        assert levels.distances(s.encode(), parts, np.arange(len(words))[::-1]).tolist() == [text.levenshtein(s, x) for x in words[::-1]]
    prints = _prints(spark, near_texts).cache()
    queries, grid = prints.where("id % 3 = 0"), ([2, 3, 4], [0.3, 0.7], [0.2, 0.5, 0.8])
    truth = spark.createDataFrame([(i, j) for i in range(0, 60, 3) for j in range(i, i + 5)], "query_id long, target_id long")
    rows = lambda strategy: sorted(map(tuple, sweep.sweep(queries, prints, truth, *grid, strategy).collect()))
    want = rows("plain")
    monkeypatch.setattr(sweep, "scored", None)
    monkeypatch.setattr(levels, "LETTERS", 300)
    assert rows("auto") == want and len({r[3:5] for r in want}) > 5


def test_f3_recursion_reaches_the_end_of_every_chain(spark, tmp_path):
    from codeprov.oracles import SQL

    from tests import oracle

    sizes = {1: 1, 2: 2, 3: 40, 4: 41, 5: 17, 6: 18, 7: 1500, None: 3}
    rows = [(u, i) for u, n in sizes.items() for i in range(n)]
    t = spark.createDataFrame([(k, u, i) for k, (u, i) in enumerate(rows)], "event_id long, user_id long, i int")
    t.select("event_id", "user_id", F.timestamp_seconds(F.col("i") % 7).cast("timestamp_ntz").alias("ts")).coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    got = {r.user_id: r.depth for r in QUERIES["O_recursive"](spark, str(tmp_path)).collect()}
    assert got == sizes | {None: 1}  # no join meets an empty key, in SQL neither
    con = oracle.duckdb.connect()
    con.sql(f"CREATE VIEW events AS SELECT * FROM '{tmp_path}/events.parquet/*.parquet'")
    assert dict(con.sql(SQL["O_recursive"]).fetchall()) == got


def test_f2_ablations_take_every_mutation(spark, copies):
    units = derive.units(spark.read.parquet(f"{copies}/part.parquet"))
    assert units.select("mutation").distinct().count() == 6
    got = {r.choice: r.pairs for r in QUERIES["B19_ablations"](spark, copies).collect()}
    for choice, options in (("canonical", {}), ("visibility kept", {"drop_visibility": False})):
        assert got[choice] == match.self_clones(fingerprints(units, "unit_id", **options), match.CONSERVATIVE).count() > 0


def test_f4_brute_force_scores_every_item(spark, monkeypatch):
    from codeprov.baselines import bruteforce

    items, docs = (spark.read.parquet(f"{SF}/{t}.parquet") for t in ("benchmark", "documents"))
    rows = QUERIES["W10_bruteforce_scores"](spark, SF).collect()
    assert len(rows) == items.count() * docs.count() and {r.item_id for r in rows} == {r.item_id for r in items.collect()}
    g = random.Random(4)
    word = lambda: "".join(g.choices("abcd", k=g.choice([1, 2, 7, 8, 9, 16, 17, 32, 33, 64, 65, 90])))
    rows = [[(i, [word() for _ in range(g.randint(0, 4))]) for i in range(30)] for _ in range(2)]
    q, t = (spark.createDataFrame(x, "id long, subs array<string>").cache() for x in rows)
    scores = lambda: {(r.query_id, r.target_id): r.score for r in bruteforce.all_pairs(q, t).collect()}
    monkeypatch.setattr(bruteforce, "LETTERS", 300)
    found = scores()
    monkeypatch.setattr(bruteforce, "MOST_ASKED", 0)
    assert found == scores() and len(found) == 900 and None in found.values()
