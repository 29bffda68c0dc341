import itertools
import random
import re

from codeprov.llm import pii

SF = "/root/testdata/sf0.001"
PATTERNS = [re.compile(p) for p in (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", r"[0-9]([\x20-]?[0-9])+", r"\+[0-9][\x20().0-9-]+[0-9]")]


def by_pattern(text):
    out = []
    for kind, p in enumerate(PATTERNS):
        for m in p.finditer(text):
            d = re.sub("[^0-9]", "", m.group())
            if kind == 0 or kind == 1 and all(int(x) <= 255 for x in m.group().split(".")) or kind == 2 and 12 <= len(d) <= 19 and pii.luhn(d) or kind == 3 and 9 <= len(d) <= 15:
                out.append((m.start(), kind, m.end()))
    return sorted(out)


def test_base_spans_equal_the_patterns():
    rng = random.Random(1)
    for _ in range(20000):
        t = "".join(rng.choice("ab.@@-+ 1234567890.. ()\n_%é") for _ in range(rng.randint(0, 60)))
        assert pii.base_spans(t) == by_pattern(t)


def test_decoding_and_marginals_equal_enumeration():
    rng = random.Random(2)
    for _ in range(200):
        n = rng.randint(1, 6)
        segs = sorted({(i, rng.randint(i + 1, n), rng.randint(0, 3)) for i in (rng.randrange(n) for _ in range(5))})
        segs = [(*s, []) for s in segs]
        scores = [rng.uniform(-2, 2) for _ in segs]
        import math

        sets = [c for r in range(len(segs) + 1) for c in itertools.combinations(range(len(segs)), r) if all(segs[a][1] <= segs[b][0] or segs[b][1] <= segs[a][0] for a, b in itertools.combinations(c, 2))]
        total = [sum(scores[x] for x in c) for c in sets]
        best = pii.decode(n, segs, scores)
        assert abs(sum(scores[x] for x, s in enumerate(segs) if s[:3] in best) - max(total)) < 1e-9
        z = sum(map(math.exp, total))
        logz, p = pii.marginals(n, segs, scores)
        assert abs(logz - math.log(z)) < 1e-9
        for x in range(len(segs)):
            assert abs(p[x] - sum(math.exp(t) for c, t in zip(sets, total, strict=True) if x in c) / z) < 1e-9


def test_model_learns_the_kinds_and_adds_nothing_to_clean_text():
    rng = random.Random(3)
    number = lambda k: "".join(rng.choice("0123456789") for _ in range(k))

    def card():
        while not pii.luhn(n := "4" + number(15)):
            pass
        return n

    zones = [f(k) for k in range(60) for f in (lambda k: f"u{k}@mail{k}.example.com", lambda k: f"{k}.{k + 9}.3.4", lambda k: card(), lambda k: f"+1 ({number(3)}) 555-{number(4)}", lambda k: "4" + number(9), lambda k: f"{k}.0")]
    w = pii.train(zones)
    new = f"x.9@mail4.example.org {card()}"
    base, found = pii.spans(new, w)
    assert [k for _, k, _ in base] == [0, 2] and set(base) <= set(found)
    marks, segs = pii.candidates(new, 0, len(new))
    alone = [(marks[i], k, marks[j]) for i, j, k in pii.decode(len(marks) - 1, segs, pii._scores(segs, w))]
    assert alone == base
    assert pii.spans("Version 2.0 of 14 parts, 3 x 4", w) == ([], [])


def test_documents_and_redaction(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    got = {r.doc_id: r for r in pii.digest(pii.detect(docs)).collect()}
    for r in docs.collect():
        want = by_pattern(r.text)
        assert got[r.doc_id].base_sha256 == pii.sha(want)
        assert [got[r.doc_id][f"n_{k}"] for k in pii.KINDS] == [sum(x[1] == i for x in want) for i in range(4)]
    assert all(not by_pattern(r.text) for r in pii.redact(docs).collect())


def test_edges(spark):
    rows = [(1, None, "b"), (1, "", "c"), (None, "a@b.cd " * 2000 + "9" * 50000 + "." * 5 + "a" * 50000, ""), (2, "x@y.zz", None), (2, "x@y.zz", None)]
    d = spark.createDataFrame(rows, "doc_id long, text string, base string")
    got = pii.digest(pii.detect(d)).collect()
    assert sorted(r.n_email for r in got) == [0, 0, 1, 1, 2000]
    assert pii.redact(d).where("text is null").count() == 1
    assert pii.detect(d.limit(0)).count() == 0


#: What no pattern finds, with its kind; and what is no personal data.
PLANTED = [("Call (555) 123-4567 now", "(555) 123-4567", "phone"), ("Ring 212-555-0198.", "212-555-0198", "phone"), ("Write to user@localhost please", "user@localhost", "email"), ("Pay with 4111.1111.1111.1111, or", "4111.1111.1111.1111", "card"), ("my card 4111111111111112 is", "4111111111111112", "card"), ("it is 4111 1111 1111 1112 or", "4111 1111 1111 1112", "card"), ("a 4111111111111111 5500005555555559 b", "4111111111111111", "card"), ("my phone 5551234567 is", "5551234567", "phone")]
CLEAN = ["on 2024-01-31 and", "ISBN 978-3-16-148410-0", "id 1234567890 of", "from 1990-1999", "costs 1.234.567 or", "is 3.1415926535", "see 4111111111111112 of", "react@18 is"]


def test_planted_spans_outside_the_patterns_are_added_and_masked(spark):
    schema = "doc_id long, text string"
    given = [(i, t) for i, t in enumerate([t for t, _, _ in PLANTED] + CLEAN)]
    learned = [(100 + k, f"words {span} follow") for k in range(20) for span in (f"u{k}@mail{k}.example.com", f"+1 (2{k:02}) 555-{k * 37:04}", f"10.0.{k}.7")]
    for rows in (given, given + learned):
        d = spark.createDataFrame(rows, schema)
        got = {r.doc_id: r for r in pii.digest(pii.detect(d)).collect()}
        masked = {r.doc_id: r.text for r in pii.redact(d).collect()}
        for i, (text, span, kind) in enumerate(PLANTED):
            at = text.index(span)
            assert f"{kind}:{at}:{at + len(span)}" in got[i].spans.split(","), text
            assert span not in masked[i] and f"[{kind.upper()}]" in masked[i]
        assert all(not got[i].spans and masked[i] == t for i, t in given[len(PLANTED) :])


def test_the_sample_holds_every_kind():
    rows = pii.examples([("", f"+1 (2{k:02}) 555-0100", "") for k in range(50)])
    assert {s[2] for _, segments, gold in rows for s, g in zip(segments, gold, strict=True) if g} >= {0, 2, 3}
