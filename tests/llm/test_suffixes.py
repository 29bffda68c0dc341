import random

import numpy as np
import pytest
from codeprov.llm import suffixes as S

SF = "/root/testdata/sf0.001"


def ranges(r):
    return [(s.first_word, s.last_word) for s in r.spans]


def test_pieces():
    rng = np.random.default_rng(4)
    h = rng.integers(0, 1 << 63, 300, dtype=np.uint64)
    again = np.concatenate([h[:5], h[100:200], h[7:20]])
    for k in (1, 2, 5, 34, 50):
        assert (S.grams(h, k)[100 : 200 - k + 1] == S.grams(again, k)[5 : 105 - k + 1]).all()
        assert len(np.unique(S.grams(h, k))) == 300 - k + 1
    for w in (1, 2, 3, 7, 17):
        v = rng.integers(0, 9, 100)
        assert S.least_of(v, w).tolist() == [s + int(np.argmin(v[s : s + w])) for s in range(100 - w + 1)]


def test_neighbours_in_word_order():
    rng = np.random.default_rng(2)
    rows = rng.integers(0, 3, (400, 6)).astype(np.int32)
    lengths = rng.integers(0, 7, 400)
    rows[np.arange(6)[None, :] >= lengths[:, None]] = -1
    keys = rng.integers(0, 3, 400).astype(np.uint64) << np.uint64(40)
    order, common = S.common_lengths(keys, rows, lengths)
    plain = sorted(range(400), key=lambda i: (keys[i], rows[i].tolist()))
    assert [(keys[i], rows[i].tolist()) for i in order] == [(keys[i], rows[i].tolist()) for i in plain]
    for at, (i, j) in enumerate(zip(order, order[1:], strict=False), 1):
        same = next((x for x in range(6) if rows[i, x] != rows[j, x] or rows[i, x] < 0), 6)
        assert common[at] == (same if keys[i] == keys[j] else -1)


@pytest.mark.parametrize("across", [True, False])
def test_words_decide_where_hashes_meet(monkeypatch, spark, across):
    """With one hash for all words every gram meets every other; the result stays that of the words."""
    monkeypatch.setattr(S, "word_hashes", lambda words: np.full(max(1, len(words)), 7, dtype=np.uint64))
    rng = random.Random(3)
    rows = [(i, " ".join(rng.choice("ab") for _ in range(rng.randrange(40)))) for i in range(30)]
    texts = [t for _, t in rows]
    counts, kept = S.kept_suffixes(texts, 9, 4)
    split = [t.split() for t in texts]
    begins = np.cumsum(counts) - counts
    contexts = [split[k["row"]][k["at"] - begins[k["row"]] - k["most"] : k["at"] - begins[k["row"]] - k["least"] + 9] for k in kept]
    masks = S.passages(kept["key"], kept["most"].astype(np.int64), kept["row"].astype(np.int64), np.zeros(len(kept), np.uint8), contexts, 9, across)
    starts = [[] for _ in rows]
    for k, m in zip(kept, masks.tolist(), strict=True):
        starts[k["row"]] += [k["at"] - begins[k["row"]] - o for o in range(64) if m >> o & 1]
    assert len(set(kept["key"].tolist())) == 1
    assert [S._marked(len(w), np.array(sorted(s), dtype=np.int64), 9) for w, s in zip(split, starts, strict=True)] == S.brute_force(rows, 9, across)


@pytest.mark.parametrize(("words", "gram", "across", "hot"), [(50, 16, True, 50_000), (50, 16, False, 50_000), (50, 34, True, 3), (8, 5, True, 1), (4, 1, False, 2)])
def test_documents_against_brute_force(spark, words, gram, across, hot):
    docs = spark.read.parquet(f"{SF}/documents.parquet").limit(120)
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    want = dict(zip([i for i, _ in rows], S.brute_force(rows, words, across), strict=True))
    d = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r for r in S.repeated_passages(d, words, gram, across, 60_000, 50_000, hot).collect()}
    assert {i: ranges(r) for i, r in got.items()} == want
    assert any(want.values())


def test_planted_passages_and_edges(spark):
    rng = random.Random(9)
    fresh = lambda n: " ".join(f"w{rng.randrange(10**9)}" for _ in range(n))
    passage = fresh(55)
    rows = [(1, f"{fresh(70)} {passage} {fresh(10)}", "a"), (2, f"{passage}\n{fresh(200)}", None), (3, fresh(300), ""), (4, None, ""), (4, "", ""), (None, fresh(60), ""), (6, "same " * 49, ""), (6, "same " * 49, ""), (7, fresh(20000), "")]
    d = spark.createDataFrame(rows, "doc_id long, text string, spans string")
    got = S.repeated_passages(d).collect()
    assert len(got) == len(rows)
    by = {r.doc_id: r for r in got}
    assert ranges(by[1]) == [(70, 125)] and ranges(by[2]) == [(0, 55)]
    assert rows[0][1][by[1].spans[0].start : by[1].spans[0].end] == passage
    assert sum(r.n_spans for r in got) == 2
    assert S.repeated_passages(d.limit(0)).count() == 0
