import hashlib
import random

import numpy as np
import public_tokenizers as P
import pytest
import tiktoken
from codeprov.llm import bpe

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def ranks(spark):
    return bpe.read_ranks(spark, P.path(bpe.VOCABULARY))


@pytest.fixture(scope="module")
def theirs(ranks):
    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=dict(ranks), special_tokens={})


def test_perfect_hash(ranks):
    h = bpe.PerfectHash([b for b, _ in ranks])
    assert sorted(h.slots) == list(range(len(ranks)))
    assert all(h.find(b) == i for i, (b, _) in enumerate(ranks))
    assert h.find(b"\xff\xfe\xfd no such token") == -1


def test_random_strings_equal_the_library(ranks, theirs):
    rng = random.Random(7)
    c = bpe.Codec(ranks, P.PATTERN)
    pool = "abcdefgh theéèñß 漢字🙂\n\t'sÇ0123456789.,-|<endoftext>"
    for k in range(400):
        t = "".join(rng.choice(pool) for _ in range(rng.choice([0, 1, 5, 40, 700])))
        if k == 0:
            t = "<|endoftext|>" + "ab" * 3000
        got = np.frombuffer(c.encode(t), dtype="<u4").tolist()
        assert got == theirs.encode_ordinary(t)
        assert c.decode(c.encode(t)).decode() == t


def test_both_cutters_agree(ranks, theirs):
    c = bpe.Codec(ranks, P.PATTERN)
    rng = random.Random(8)
    pool = [*map(chr, range(256)), " ", " ", "'", "s", "\n"]
    for _ in range(300):
        t = "".join(rng.choice(pool) for _ in range(60))
        assert c.narrow(t) == c.wide(t) == c.cut(t)
        assert np.frombuffer(c.encode(t), dtype="<u4").tolist() == theirs.encode_ordinary(t)
    assert bpe.narrow(r"\p{Lu}+|.") is None and bpe.narrow(r"(?i:a)|[^\s]") is None


def test_the_kept_table_stays_small(ranks, theirs, monkeypatch):
    monkeypatch.setattr(bpe, "KEPT", 5)
    c = bpe.Codec(ranks, P.PATTERN)
    t = " ".join(f"word{i % 17} zq{i % 11}x" for i in range(300))
    assert np.frombuffer(c.encode(t), dtype="<u4").tolist() == theirs.encode_ordinary(t)
    assert len(c.known) <= 5 and len(c.known.former) <= 5


def test_documents_equal_the_library(spark, theirs):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    got = {r.doc_id: r for r in bpe.encode(docs).collect()}
    for r in docs.collect():
        ids = theirs.encode_ordinary(r.text)
        x = got[r.doc_id]
        assert x.ids == ids and x.n_tokens == len(ids)
        assert x.ids_sha256 == hashlib.sha256(np.array(ids, dtype="<u4").tobytes()).hexdigest()
        assert x.decoded_sha256 == hashlib.sha256(r.text.encode()).hexdigest()
    back = bpe.decode(bpe.encode(docs)).select("doc_id", "text")
    assert back.exceptAll(docs.select("doc_id", "text")).count() == 0


def test_edges(spark):
    rows = [(1, None, "a"), (1, "", None), (None, "x" * 100_000, "b"), (2, "same", ""), (2, "same", "")]
    got = bpe.encode(spark.createDataFrame(rows, "doc_id long, text string, ids string")).collect()
    assert len(got) == 5 and sorted(r.n_tokens for r in got)[:2] == [0, 0]
    assert bpe.encode(spark.createDataFrame([], "doc_id long, text string")).count() == 0
    assert bpe.encode(spark.createDataFrame(rows[3:], "doc_id long, text string, ids string"), as_binary=True).first().ids
