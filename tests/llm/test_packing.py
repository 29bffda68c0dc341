import random

import numpy as np
import pytest
from codeprov.llm import bpe, packing

SF = "/root/testdata/sf0.001"


def test_best_fit_decreasing_equals_a_plain_search():
    rng = random.Random(1)
    for _ in range(150):
        length = rng.choice([1, 2, 5, 16, 100, 2048])
        sizes = [rng.randint(1, length) for _ in range(rng.randint(0, 120))]
        free: list[int] = []
        for n in sorted(sizes, reverse=True):
            fits = [f for f in free if f >= n]
            if fits:
                free[free.index(min(fits))] -= n
            else:
                free.append(length - n)
        got = packing.best_fit_decreasing(sizes, length)
        assert sorted(i for b in got for i in b) == list(range(len(sizes)))
        assert sorted(length - sum(sizes[i] for i in b) for b in got) == sorted(free)


@pytest.mark.parametrize(("length", "shard_bytes"), [(2048, 8 << 20), (64, 100_000)])
def test_round_trip(spark, length, shard_bytes):
    docs = spark.read.parquet(f"{SF}/documents.parquet").limit(80)
    packed = packing.pack(docs, length, shard_bytes=shard_bytes).cache()
    want = {r.doc_id: r.ids for r in bpe.encode(docs).collect() if r.ids}
    assert {r.doc_id: r.ids for r in packing.unpack(packed).collect()} == want
    rows = packed.collect()
    assert sum(r.n_tokens for r in rows) >= 0.9 * length * (len(rows) - packed.select("shard").distinct().count())
    for r in rows:
        places = packing.row_of(r.position_ids).tolist()
        assert len(r.input_ids) == 4 * length == 4 * len(places) and r.cu_seqlens[-1] == r.n_tokens
        for a, b in zip(r.cu_seqlens, r.cu_seqlens[1:], strict=False):
            assert places[a:b] == list(range(b - a))
    for m in packing.matrices(packed).collect():
        ids = np.frombuffer(m.ids, "<i4").reshape(m.n_sequences, m.length)
        own = sorted((r for r in rows if r.shard == m.shard), key=lambda r: r.sequence)
        assert ids.tolist() == [packing.row_of(r.input_ids).tolist() for r in own]
        at = np.frombuffer(m.cu_offsets, "<i4")
        assert np.frombuffer(m.cu_seqlens, "<i4")[at[0] : at[1]].tolist() == own[0].cu_seqlens


def test_edges(spark):
    rows = [(1, None, "", 0), (1, "", None, 1), (None, "long text " * 4000, "", 2), (2, "same", "", 3), (2, "same", "", 3)]
    d = spark.createDataFrame(rows, "doc_id long, text string, shard string, piece int")
    got = packing.pack(d, 128).collect()
    assert sum(len(r.doc_ids) for r in got) == 2 + sum(1 for r in got for x in r.doc_ids if x is None)
    assert sum(r.n_tokens for r in got) == bpe.encode(d).selectExpr("sum(n_tokens)").first()[0]
    assert packing.pack(d.limit(0)).count() == 0


def test_equal_rows_are_spread(spark):
    d = spark.createDataFrame([(None, "one two three")] * 1000, "doc_id long, text string").coalesce(1)
    salts = {r.salt for r in packing.pieces(d).collect()}
    assert salts == set(range(-(-1000 // packing.ALIKE)))
    assert sum(len(r.doc_ids) for r in packing.pack(d).collect()) == 1000
