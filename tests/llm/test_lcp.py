import hashlib

import numpy as np
from codeprov.llm import lcp

SF = "/root/testdata/sf0.001"


def test_equal_substrings_share_interior_names():
    rng = np.random.default_rng(1)
    words = ["".join(map(chr, rng.integers(97, 110, rng.integers(2, 9)))) for _ in range(900)]
    middle = " ".join(words[:600])
    one, two = "zq " * 5 + middle + " end", "Another opening of other length, " + middle + " and more" * 9
    names = []
    for text in (one, two):
        n, first = np.array([ord(c) for c in text], dtype=np.uint64), np.zeros(len(text), bool)
        first[0] = True
        levels = []
        for _ in range(4):
            n, first = lcp.parse(n, first)
            levels.append(set(n.tolist()))
        names.append(levels)
    for level in range(4):
        a, b = names[0][level], names[1][level]
        assert len(a & b) >= 0.8 * min(len(a), len(b))


def test_phrases_are_short_and_batches_do_not_matter():
    texts = ["", "a", "aaaaaaaaaaaaaaaaaaaa", "abab" * 500, "é漢🙂 mixed", "Lorem ipsum dolor " * 40]
    together = lcp.fingerprints(texts)
    for i, t in enumerate(texts):
        assert (lcp.fingerprints([t])[0] == together[i]).all()
    n, first = np.random.default_rng(2).integers(0, 5, 20000).astype(np.uint64), np.zeros(20000, bool)
    first[0] = True
    got, _ = lcp.parse(n, first)
    assert 20000 / 12 < len(got) < 20000 / 2
    assert lcp.likeness(together, together).tolist() == [1.0] * len(texts)
    assert lcp.likeness_of(lcp.shown(together)[4], lcp.shown(together)[4]) == 1.0


def test_documents_against_one_process(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = sorted(docs.collect(), key=lambda r: r.doc_id)
    for bytes_ in (lcp.BUCKET_BYTES, 20_000):
        got = {r.doc_id: r for r in lcp.compare_with_edits(docs, bytes_).collect()}
        assert len(got) == len(rows)
        for r, after in zip(rows, rows[1:] + rows[:1], strict=True):
            x, half = got[r.doc_id], len(r.text) // 2
            e = r.text[: len(r.text) - half] + after.text[:half]
            f = lcp.fingerprints([r.text, e, after.text])
            assert x.n_chars == len(r.text) and x.edited_sha256 == hashlib.sha256(e.encode()).hexdigest()
            assert [x.fingerprint, x.edited_fingerprint] == lcp.shown(f[:2])
            assert x.near_edited == lcp.likeness(f[:1], f[1:2])[0] and x.near_next == lcp.likeness(f[:1], f[2:])[0]


def test_edges(spark):
    schema = "doc_id long, text string, key string, own int, bucket string"
    one = spark.createDataFrame([(5, "abcdef", "", 0, "")], schema)
    r = lcp.compare_with_edits(one).first()
    assert r.edited_sha256 == hashlib.sha256(b"abcabc").hexdigest()
    rows = [(1, None, "", 0, ""), (1, "", "", 0, None), (None, "x" * 100_000, None, 0, ""), (2, "same", "", 0, ""), (2, "same", "", 0, "")]
    got = lcp.compare_with_edits(spark.createDataFrame(rows, schema)).collect()
    assert len(got) == 5 and len({r.fingerprint for r in got if r.doc_id == 2}) == 1
    assert lcp.compare_with_edits(one.limit(0)).count() == 0


def test_long_texts_without_common_parts_stay_apart():
    rng = np.random.default_rng(3)
    texts = ["".join(map(chr, rng.integers(97, 123, 3_000_000))) for _ in range(2)]
    prints = lcp.fingerprints(texts)
    assert lcp.likeness(prints[:1], prints[1:])[0] < 0.05
    assert lcp.likeness_of(*lcp.shown(prints)) == lcp.likeness(prints[:1], prints[1:])[0]
