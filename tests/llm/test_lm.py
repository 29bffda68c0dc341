import math
import random
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from codeprov.llm import lm

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize(("n", "most"), [(1, 5), (10, 100), (1000, 10**6), (3000, 2**63), (1000, 1200), (700, 2**64 - 1)])
def test_elias_fano(tmp_path, n, most):
    rng = np.random.default_rng(n)
    v = np.unique(rng.integers(0, most, n, dtype=np.uint64))
    lm.EliasFano.build(v, most).save(str(tmp_path), "x")
    e = lm.EliasFano.open(str(tmp_path), "x")
    assert (e.access(np.arange(len(v))) == v).all()
    q = np.concatenate([v, rng.integers(0, most, 1000, dtype=np.uint64)])
    at = {int(x): i for i, x in enumerate(v)}
    assert e.find(q).tolist() == [at.get(int(x), -1) for x in q]
    again = np.sort(rng.integers(0, 50, n, dtype=np.uint64))
    assert (lm.EliasFano.build(again, 50).access(np.arange(n)) == again).all()


def brute(rows, order):
    """Counts in dictionaries; discounted probabilities as quantised."""
    words = {i: (t or "").encode().lower().split() for i, t in rows}
    train = [i for i in words if zlib.crc32(str(i).encode()) % 7 != 2]
    c, after = Counter(), defaultdict(Counter)
    grams = lambda w, m: zip(*(([lm.START] * (m - 1) + [*w, lm.END])[x:] for x in range(m)), strict=False)
    for i in train:
        c.update([*words[i], lm.END])
        for m in range(2, order + 1):
            for *u, w in grams(words[i], m):
                after[tuple(u)][w] += 1
    n, v = sum(c.values()), len(c)
    seen = {u: {w: float(lm.VALUES[lm.quantise(np.array([(k - lm.DISCOUNT) / own.total()]))[0]]) for w, k in own.items()} for u, own in after.items()}

    def p(w, u):
        if not u:
            return (c[w] + 1) / (n + v + 1)
        own = seen.get(u, {})
        return own.get(w, 0.0) + (1 - sum(own.values())) * p(w, u[1:])

    out = {}
    for i, ws in words.items():
        seq = [*ws, lm.END]
        out[i] = (len(seq), sum(c[t] > 0 for t in seq), n, sum(math.log10(p(t, ())) for t in seq), sum(math.log10(p(w, tuple(u))) for *u, w in grams(ws, order)))
    return out, p, c, after


def test_probabilities_sum_to_one():
    rng = random.Random(5)
    rows = [(i, " ".join(rng.choice("abcdefg") for _ in range(rng.randrange(30)))) for i in range(60)]
    _, p, c, after = brute(rows, 3)
    assert len(after) > 20
    for u in after:
        assert sum(p(w, u) for w in [*c, "never seen"]) == pytest.approx(1)
    x = np.array([1.0, 0.3, 1e-9, 1e-13])
    found = lm.VALUES[lm.quantise(x)]
    assert (found <= x * (1 + 1e-9)).all() and (found[:3] > x[:3] * 10**-lm.STEP / 1.0001).all() and found[3] == 0


@pytest.mark.parametrize(("batch", "shard", "order"), [(8 << 20, 12 << 20, 2), (100_000, 60_000, 2), (200_000, 50_000, 3)])
def test_documents_against_brute_force(spark, batch, shard, order):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    want, *_ = brute(rows, order)
    got = lm.score(docs, order=order, batch_bytes=batch, shard_bytes=shard).collect()
    assert len(got) == len(rows)
    for r in got:
        w = want[r.doc_id]
        assert (r.n_tokens, r.n_known, r.train_tokens) == w[:3]
        assert r.base_score == pytest.approx(w[3]) and r.score == pytest.approx(w[4], rel=1e-5)
    held = [r for r in got if r.held_out]
    assert sum(r.score for r in held) > sum(r.base_score for r in held)


def test_a_stored_model_scores_alike(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    lm.fit(docs, batch_bytes=300_000, shard_bytes=90_000).write.parquet(f"{tmp_path}/model")
    model = spark.read.parquet(f"{tmp_path}/model")
    assert model.where("shard >= 0").count() > 3
    want = {r.doc_id: r for r in lm.score(docs, batch_bytes=150_000, shard_bytes=90_000).collect()}
    got = lm.score(docs.where("doc_id < 50"), batch_bytes=40_000, model=model).collect()
    assert got and all((r.n_known, r.train_tokens) == (want[r.doc_id].n_known, want[r.doc_id].train_tokens) and r.score == pytest.approx(want[r.doc_id].score, rel=1e-5) for r in got)
    other = lm.score(spark.createDataFrame([(1, "zzqx unheard of"), (2, None)], "doc_id long, text string"), model=model).collect()
    assert sorted((r.n_tokens, r.score < 0) for r in other) == [(1, True), (4, True)]


def test_edges(spark):
    schema = "doc_id long, text string, batch string, held_out int"
    rows = [(1, None, "", 0), (1, "", "", 0), (None, "A b " * 50000, None, None), (2, "a B", "", 0), (2, "a B", "", 0)]
    got = lm.score(spark.createDataFrame(rows, schema)).collect()
    assert sorted(r.n_tokens for r in got) == [1, 1, 3, 3, 100001]
    assert lm.score(spark.createDataFrame([], schema)).count() == 0
