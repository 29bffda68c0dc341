import zlib

import pytest
from codeprov.llm import langid

SF = "/root/testdata/sf0.001"
SAMPLES = {"aa": "the cat sat on the mat and the dog ran to the hill " * 3, "bb": "le chat est assis sur le tapis et le chien va vers la colline " * 2}


def phrases(text, sample):
    n = i = 0
    while i < len(text):
        j = i + 1
        while j <= len(text) and text[i:j] in sample:
            j += 1
        n, i = n + 1, max(j - 1, i + 1)
    return n


@pytest.mark.parametrize("text", ["the cat", "le chien", "zzz the qq", "x", "the cat sat on the mat and le chat est assis vers the hill", "漢字 the"])
def test_phrases_by_definition(text):
    m = langid.Model(SAMPLES)
    shown = lambda t: "".join(map(chr, m.alphabet.classes(t)))
    assert m.phrases([text])[0].tolist() == [phrases(shown(text), shown(SAMPLES[k])) for k in m.languages]


@pytest.mark.parametrize("block", [2048, 50, 3, 1])
def test_long_texts_are_parsed_whole(monkeypatch, block):
    monkeypatch.setattr(langid, "BLOCK", block)
    m = langid.Model(SAMPLES)
    shown = lambda t: "".join(map(chr, m.alphabet.classes(t)))
    texts = [("the cat sat on the hill and le chien est la " * 400)[:9000], "the", SAMPLES["aa"] * 20, "", "qq 漢字 x " * 300]
    want = [[phrases(shown(t), shown(SAMPLES[k])) for k in m.languages] for t in texts]
    assert m.phrases(texts).tolist() == want
    assert [m._in_order(m.alphabet.classes(t)) for t in texts] == want


def test_held_out_accuracy(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    got = {r.doc_id: r for r in langid.identify(docs).collect()}
    rows = docs.collect()
    assert len(got) == len(rows)
    assert all(got[r.doc_id].held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) for r in rows)
    held = [r for r in rows if got[r.doc_id].held_out]
    assert sum(got[r.doc_id].lang_pred == r.lang for r in held) >= 0.95 * len(held)
    assert all(0 <= r.score <= 1 for r in got.values())


def test_edges(spark):
    schema = "doc_id long, text string, lang string, held_out int, score string"
    rows = [(1, None, "en", 1, ""), (2, "12 -- 3", "en", 1, ""), (None, "the cat sat", None, 1, ""), (4, "le chat " * 40000, "fr", 1, None), (4, "the mat", "en", 0, "")]
    got = langid.predict(spark.createDataFrame(rows, schema), SAMPLES).collect()
    assert [(r.doc_id, r.lang_pred) for r in got] == [(1, "und"), (2, "und"), (None, "aa"), (4, "bb"), (4, "aa")]
    assert {r.lang_pred for r in langid.identify(spark.createDataFrame([(1, "abc", None)], "doc_id long, text string, lang string")).collect()} == {"und"}
    assert langid.identify(spark.createDataFrame([], "doc_id long, text string, lang string")).count() == 0


def invented(k, n):
    """``n`` letters or more of a language of its own."""
    import random

    rng = random.Random(k)
    words = ["".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(rng.randint(2, 7))) for _ in range(40)]
    return " ".join(rng.choice(words) for _ in range(n // 3))


def test_languages_of_long_documents_are_learned(spark):
    texts = {"short": invented(1, 900), "long": invented(2, 60000), "copies": invented(3, 60000)}
    rows = [("short", f"{texts['short']} {i}") for i in range(20)] + [("long", f"{texts['long']} x{'y' * i}") for i in range(20)] + [("copies", texts["copies"])] * 400
    samples = langid.fit(spark.createDataFrame(rows, "lang string, text string"))
    assert set(samples) == set(texts) and all(0 < len(s) <= langid.SAMPLE_CHARS for s in samples.values())
    assert len(samples["long"]) > langid.SAMPLE_CHARS // 2 and len(samples["copies"]) > langid.SAMPLE_CHARS // 2
    docs = spark.createDataFrame([(k, t[500:900]) for k, t in texts.items()], "doc_id string, text string")
    assert all(r.lang_pred == r.doc_id for r in langid.predict(docs, samples).collect())


def test_more_languages_than_the_full_bound_share_it(spark):
    n = langid.FULL_LANGUAGES + 16
    rows = [(f"l{k:03}", invented(k, 1500)) for k in range(n) for _ in range(1 + k % 2)]
    samples = langid.fit(spark.createDataFrame(rows, "lang string, text string"))
    assert len(samples) == n and sum(map(len, samples.values())) <= langid.SAMPLE_CHARS * langid.FULL_LANGUAGES
    docs = spark.createDataFrame([(k, t[:300]) for k, t in rows], "doc_id string, text string")
    assert all(r.lang_pred == r.doc_id for r in langid.predict(docs, samples).collect())
