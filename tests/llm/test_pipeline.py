import corpus_pipeline as C
from codeprov.llm import decontaminate, pii, simhash

SF = "/root/testdata/sf0.001"


def test_stages_against_brute_force(spark):
    rows = {r.doc_id: r for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    kept = {i: r.text for i, r in rows.items() if any(c.isalpha() for c in r.text)}
    groups = simhash.brute_force(kept)
    kept = {i: t for i, t in kept.items() if groups[i][1] == i}
    hits = decontaminate.brute_force(list(kept.items()), items)
    kept = {i: t for i, t in kept.items() if not hits[i][4]}
    got = {r.doc_id: r for r in C.run(spark, SF).collect()}
    assert set(got) == set(kept)
    import hashlib

    clean = [i for i, t in kept.items() if not pii.base_spans(t)]
    assert all(got[i].decoded_sha256 == hashlib.sha256(kept[i].encode()).hexdigest() for i in clean)
    assert all(got[i].decoded_sha256 != hashlib.sha256(kept[i].encode()).hexdigest() for i in set(kept) - set(clean))


def test_repeated_null_and_empty_rows(spark):
    schema = "doc_id long, text string, lang string, source string, n_chars long, extra string"
    d = spark.createDataFrame([(1, "a b c d", "en", None, 7, "x"), (1, "a b c d", "en", None, 7, "x"), (2, None, None, None, None, None), (3, "1 2 3", "en", "s", 5, ""), (None, "e f g", None, "", 1, "")], schema)
    for rows in (d, d.limit(0)):
        x = rows
        for _, stage in C.STAGES[:4]:
            x = stage(spark, x, SF)
            assert x.columns == d.columns
        assert x.count() == (2 if rows is d else 0)
