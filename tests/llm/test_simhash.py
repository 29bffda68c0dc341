import random

import numpy as np
import pytest
from codeprov.llm import simhash

SF = "/root/testdata/sf0.001"


def test_code_words_meet_at_one_error():
    g = simhash.golay()
    assert (g.leader >= 0).all()
    rng = np.random.default_rng(1)
    v = rng.integers(0, 1 << 23, 3000)
    w = v ^ (1 << rng.integers(0, 23, 3000))
    assert all(a in set(b) for a, b in zip(g.filed(v), g.looked_up(w), strict=True))


def test_pairs_up_to_three_bits_share_a_key():
    rng = random.Random(2)
    for _ in range(300):
        a = rng.getrandbits(64)
        b = a
        for i in rng.sample(range(64), rng.randint(0, 3)):
            b ^= 1 << i
        _, filed = simhash.keys(np.array([a], dtype=np.uint64), False)
        _, asked = simhash.keys(np.array([b], dtype=np.uint64), True)
        assert set(filed) & set(asked)


def test_equals_brute_force_on_documents(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    want = simhash.brute_force({r.doc_id: r.text for r in docs.collect()})
    got = {r.doc_id: (r.fingerprint, r.component_id) for r in simhash.near_duplicates(docs).collect()}
    assert got == want


def test_planted_fingerprints_link_as_by_brute_force(spark):
    rng = random.Random(3)
    fps = []
    for _ in range(60):
        a = rng.getrandbits(64)
        fps.append(a)
        for _ in range(4):
            b = a
            for i in rng.sample(range(64), rng.randint(1, 5)):
                b ^= 1 << i
            fps.append(b)
    signed = sorted({f - (1 << 64) if f >> 63 else f for f in fps})
    got = [tuple(r) for r in simhash.links(spark.createDataFrame([(f,) for f in signed], "fp long")).collect()]
    want = {(a, b) for a in signed for b in signed if a < b and ((a ^ b) & (2**64 - 1)).bit_count() <= 3}
    assert len(got) == len(set(got)) and set(got) == want


def test_edges(spark):
    schema = "doc_id long, text string, lang string, fp string, node long"
    rows = [(1, None, None, "x", 1), (2, "", None, None, 1), (3, " \n", "en", "", 2), (4, "one two", None, "", 3), (5, "ONE TWO", None, "", 3), (5, "ONE TWO", None, "", 3), (None, "one two", None, "", 4), (7, "word " * 30000, "", "", 5)]
    got = simhash.near_duplicates(spark.createDataFrame(rows, schema)).collect()
    by = {r.doc_id: r for r in got}
    assert len(got) == len(rows)
    assert {by[i].component_id for i in (1, 2, 3)} == {1} and by[1].fingerprint == "0" * 16
    assert {by[i].component_id for i in (4, 5, None)} == {4}
    assert simhash.near_duplicates(spark.createDataFrame([], schema)).count() == 0


@pytest.mark.parametrize("n", [0, 1, 2, 3, 50])
def test_fingerprint_by_definition(n):
    import xxhash

    words = [f"W{i % 7}" for i in range(n)]
    text = "\t".join(words)
    low = [w.lower() for w in words]
    grams = [" ".join(low[i : i + 3]) for i in range(n - 2)] if n >= 3 else [" ".join(low)] * bool(n)
    h = [xxhash.xxh64_intdigest(g, 42) for g in grams]
    assert simhash.fingerprint(text) == sum(1 << b for b in range(64) if sum(x >> b & 1 for x in h) * 2 > len(h))
