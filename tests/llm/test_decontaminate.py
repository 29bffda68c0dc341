import random

from codeprov.llm import decontaminate as D

SF = "/root/testdata/sf0.001"


def rows(df):
    return {r.doc_id: tuple(r)[1:] for r in D.digest(df).collect()}


def test_equals_brute_force_on_documents(spark):
    docs, bench = (spark.read.parquet(f"{SF}/{t}.parquet") for t in ("documents", "benchmark"))
    want = D.brute_force([(r.doc_id, r.text) for r in docs.collect()], [(r.item_id, r.text) for r in bench.collect()])
    got = rows(D.contamination(docs, bench))
    assert got == want and any(v[4] for v in got.values())


def test_random_words_and_blocks(spark):
    rng = random.Random(5)
    word = lambda: rng.choice("a b c".split())
    items = [(i, " ".join(word() for _ in range(rng.choice([0, 1, 2, 3, 5, 13, 14, 20])))) for i in range(40)] + [(40, None), (3, "a b a b c c b a")]
    docs = [(i, " ".join(word() for _ in range(rng.randint(0, 60)))) for i in range(80)] + [(80, None), (81, ""), (82, ".,;")]
    want = D.brute_force(docs, items)
    d, b = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    assert rows(D.contamination(d, b)) == want
    assert rows(D.contamination(d, b, item_bytes=100)) == want


def test_edges(spark):
    schema = "doc_id long, text string, _hits string, items long, item_id long, n_words int"
    line = " ".join(f"w{i}" for i in range(13))
    d = spark.createDataFrame([(1, line.upper(), None, 1, 1, 1), (1, line.upper(), None, 1, 1, 1), (None, "x " + line.replace(" ", "--"), "", 2, 2, 2), (2, "é " * 200000, "", 3, 3, 3)], schema)
    b = spark.createDataFrame([(7, line, 1), (7, line, 2), (None, "é", 1)], "item_id long, text string, doc_id int")
    got = D.contamination(d, b).collect()
    assert sorted((r.doc_id or 0, r.n_words, r.n_hit, r.n_items) for r in got) == [(0, 14, 13, 1), (1, 13, 13, 1), (1, 13, 13, 1), (2, 200000, 0, 0)]
    assert D.contamination(d.limit(0), b).count() == 0
    assert {r.contaminated for r in D.contamination(d, b.limit(0)).collect()} == {False}
