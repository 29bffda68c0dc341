import random

import pytest
from codeprov.baselines import bruteforce
from codeprov.clone import candidates, fingerprint, fuzzyhash, match
from codeprov.clone.ngram import grams
from codeprov.clone.score import delta, order_free, order_free_bounded
from codeprov.functions import text
from codeprov.lang import frontend
from codeprov.operators import joins
from pyspark.sql import functions as F


def score(spark, q, t, **o):
    return spark.createDataFrame([(q, t)], "q array<string>, t array<string>").select(order_free("q", "t", **o).alias("s")).first().s


def test_delta(spark):
    rows = [("abcd", "abce", 75.0), ("abcd", "", 0.0), ("", "", 100.0)]
    got = spark.createDataFrame(rows, "a string, b string, d double").select("d", delta("a", "b").alias("x")).collect()
    assert all(r.d == r.x for r in got)


def test_order_free_examples(spark):
    assert score(spark, ["abcd", "xy"], ["xy", "abce"]) == 87.5
    assert score(spark, ["ab"], ["ab", "cdef"]) == 100
    assert score(spark, ["ab"], ["ab", "cdef"], direction="backward") == 50
    assert score(spark, ["ab", "ab", "zz"], ["ab"]) == pytest.approx(200 / 3)
    assert score(spark, ["ab", "ab", "zz"], ["ab"], collapse_equal=True) == 50
    assert score(spark, [], ["ab"]) is None and score(spark, ["ab"], []) == 0


def test_order_does_not_matter_and_twins_agree(spark):
    rng = random.Random(1)
    part = lambda: "".join(rng.choice("abcd") for _ in range(rng.randint(1, 7)))
    rows = [([part() for _ in range(rng.randint(1, 5))], [part() for _ in range(rng.randint(1, 5))]) for _ in range(150)]
    df = spark.createDataFrame(rows, "q array<string>, t array<string>")
    for r in df.select("q", "t", order_free("q", "t").alias("s"), order_free(F.shuffle("q"), F.shuffle("t")).alias("p"), order_free("q", "q").alias("own"), order_free_bounded("q", "t", 0.7).alias("b")).collect():
        assert r.s == pytest.approx(r.p) == pytest.approx(text.order_free(r.q, r.t)) and r.own == 100
        assert (r.b is None) == (r.s < 70) and (r.b is None or r.b == pytest.approx(r.s))


def test_grams_and_short_parts(spark):
    d = spark.createDataFrame([(["abcd", "ab", "bcd"],), (["ab"],), ([],)], "s array<string>").select(grams("s", 3).alias("g")).collect()
    assert [sorted(r.g) for r in d] == [["abc", "bcd"], [], []]


@pytest.mark.parametrize("eta", [0.1, 0.5, 0.7, 1.0])
def test_prefix_equals_plain(spark, eta):
    rng = random.Random(2)
    rows = [(i, ["".join(rng.choice("abcde") for _ in range(rng.randint(1, 12))) for _ in range(3)]) for i in range(60)]
    d = spark.createDataFrame(rows, "id long, subs array<string>")
    key = lambda df: sorted((r.query_id, r.target_id, r.shared, r.n_grams) for r in df.collect())
    assert key(candidates.retrieve(d, d, 3, eta, "prefix")) == key(candidates.retrieve(d, d, 3, eta, "plain"))
    assert key(candidates.retrieve(d, d, 3, eta, "prefix", most_broadcast=0)) == key(candidates.retrieve(d, d, 3, eta, "plain"))
    assert set(key(candidates.retrieve(d, d, 3, eta, "minhash"))) <= set(key(candidates.retrieve(d, d, 3, eta, "plain")))


def test_empty_inputs(spark):
    d = spark.createDataFrame([], "id long, subs array<string>")
    assert match.find_clones(d, d).count() == 0


def test_fuzzy_hash_is_local():
    a = b"a longer token stream that is cut where its content says so, and nowhere else at all"
    b = a[:40] + b"X" + a[40:]
    one, two = fuzzyhash.ctph(a), fuzzyhash.ctph(b)
    assert one[:6] == two[:6] and one[-6:] == two[-6:] and one != two
    assert len(fuzzyhash.fixed7(b"0123456789")) == 2 and fuzzyhash.ctph(b"") == ""


def test_canonical_names():
    a = "contract Box { uint sum; function put(uint x, address who) public payable { sum += x * 2; who.transfer(x); note(\"hi\"); } }"
    b = "contract Chest{uint total;\n function store(uint much, address to) external { total += much * 2; // kept\n to.transfer(much); note(\"other\"); } }"
    assert frontend.canonical_parts(a) == frontend.canonical_parts(b)
    assert frontend.canonical_parts(a) != frontend.canonical_parts(a.replace("* 2", "* 3"))
    assert frontend.canonical_parts(a, names="keep") != frontend.canonical_parts(b, names="keep")
    assert frontend.clone_type(a, a.replace(" ", "\n")) == "I" and frontend.clone_type(a, b) == "II"
    assert frontend.canonical_parts("bank.pay(sum)")[0] == ["uint", ".", "pay", "uint"]


@pytest.mark.parametrize("strategy", ["auto", "plain", "prefix"])
def test_short_fingerprints_match_their_equals_only(spark, strategy):
    rows = [(1, ["a"]), (2, ["a"]), (3, ["ab", "c"]), (4, ["ab", "c"]), (5, ["abc"]), (6, ["b"]), (7, []), (8, []), (9, ["a", "abcd"])]
    d = spark.createDataFrame(rows, "id long, subs array<string>")
    got = {(r.query_id, r.target_id, r.shared, r.n_grams, r.score) for r in match.self_clones(d, strategy=strategy).collect()}
    assert {(q, t) for q, t, *_ in got if {q, t} & {1, 2, 3, 4, 6, 7, 8}} == {(1, 2), (2, 1), (3, 4), (4, 3)}
    assert {x[2:] for x in got if x[0] < 5} == {(1, 1, 100.0)}


@pytest.mark.parametrize("rounding", ["exact", "up", "down"])
def test_prefix_equals_plain_for_each_rounding(spark, rounding):
    q = spark.createDataFrame([(1, ["abcde"]), (2, ["vwxyz"])], "id long, subs array<string>")
    t = spark.createDataFrame([(10, ["abcq"]), (11, ["bcdq"]), (12, ["cdeq"]), (13, ["abcd"]), (14, ["uvwx"])], "id long, subs array<string>")
    plain, prefix = ({(r.query_id, r.target_id, r.shared) for r in candidates.retrieve(q, t, eta=0.5, strategy=s, rounding=rounding).collect()} for s in ("plain", "prefix"))
    assert plain == prefix and len(plain) == (5 if rounding == "down" else 1)


def test_units_are_joined_by_colons(spark):
    rows = [(1, "One two. Three!\n\nFour\n...\nfive six"), (2, "...\n\n"), (3, None), (4, "a. b")]
    d = spark.createDataFrame(rows, "id long, text string")
    flat = {r.id: r for r in fingerprint.build(d, "id").collect()}
    got = {r.id: r for r in fingerprint.build(d, "id", units=True).collect()}
    a, b, c, e = flat[1].subs
    assert got[1].fp == f"{a}.{b}:{c}:{e}" and [got[i].n_units for i in (1, 2, 3, 4)] == [3, 0, 0, 1]
    assert all(got[i].subs == flat[i].subs and got[i].fp.replace(":", ".") == flat[i].fp for i in flat)


def test_broadcast_in_blocks_gives_the_same_pairs(spark):
    d = spark.createDataFrame([(i, [f"ab{i % 3}"]) for i in range(20)], "id long, subs array<string>")
    blocks = joins.broadcast_blocks(d, "20", most=100)
    assert len(blocks) == 4 and sorted(r.id for b in blocks for r in b.collect()) == list(range(20))
    assert bruteforce.all_pairs(d, d).count() == 400
