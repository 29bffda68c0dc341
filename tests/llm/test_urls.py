import random
from datetime import datetime, timedelta

import duckdb
from codeprov.llm import queries, urls

SF = "/root/testdata/sf0.001"
DAY = datetime(2024, 1, 1)


def test_query_equals_sql(spark):
    duckdb.sql(f"CREATE OR REPLACE VIEW pages AS SELECT * FROM '{SF}/pages.parquet'")
    got = queries.QUERIES["op5_url_list_filter"](spark, SF)
    want = duckdb.sql(queries.SQL["op5_url_list_filter"])
    assert sorted(got.columns) == sorted(want.columns)
    names = got.columns
    assert sorted(map(repr, (tuple(r) for r in got.collect()))) == sorted(map(repr, want.select(*names).fetchall()))


def active(entry, events, t):
    on = False
    for at in sorted({a for e, _, a in events if e == entry}):
        if at <= t:
            on = {x for e, x, a in events if e == entry and a == at} == {"add"}
    return on


def test_against_replay(spark):
    rng = random.Random(3)
    names = ["a.org", "x.a.org", "org", "x.a.org/p", "x.a.org/p/q", "b.com", "b.com/p"]
    events = [(rng.choice(names), rng.choice(["add", "remove"]), DAY + timedelta(days=rng.randrange(12))) for _ in range(60)]
    found = [f"http{rng.choice(['', 's'])}://{rng.choice(['X.a.org', 'u@a.org:80', 'b.com', 'y.b.com'])}{rng.choice(['', '/', '/p', '/p/q?x=/z', '//p/q/r#f'])}" for _ in range(60)]
    caps = [(i, u, DAY + timedelta(days=rng.randrange(13))) for i, u in enumerate(found)]
    for most in (urls.MOST_BROADCAST, 0):
        got = urls.evaluate(spark.createDataFrame(caps, "i long, url string, fetched_at timestamp_ntz"), spark.createDataFrame(events, "entry string, action string, at timestamp_ntz"), most_broadcast=most).collect()
        assert len(got) == len(caps)
        for r in got:
            rest = r.url.split("://")[1].split("?")[0].split("#")[0]
            where, _, tail = rest.partition("/")
            where = where.split("@")[-1].split(":")[0].lower()
            labels, parts = where.split("."), [x for x in tail.split("/") if x]
            keys = [".".join(labels[k:]) for k in range(len(labels))] + [where + "/" + "/".join(parts[:k]) for k in range(1, len(parts) + 1)]
            hits = [k for k in keys if active(k, events, r.fetched_at)]
            assert (r.n_active, r.entry, r.blocked) == (len(hits), max(hits, key=lambda x: (len(x), x)) if hits else None, bool(hits))


def test_edges(spark):
    caps = spark.createDataFrame([(1, None, DAY, "h"), (1, "no url", DAY, None), (2, "http://a.b/", None, ""), (2, "http://a.b/", None, ""), (3, "http://a.b/" + "s/" * 50000, DAY, "")], "page_id long, url string, fetched_at timestamp_ntz, entry string")
    entries = spark.createDataFrame([("a.b", "add", DAY), ("a.b", "add", DAY), (None, "add", DAY), ("b", "add", None), ("b", "other", DAY)], "entry string, action string, at timestamp_ntz")
    got = urls.evaluate(caps, entries).collect()
    assert sorted((r.page_id, r.n_active) for r in got) == [(1, 0), (1, 0), (2, 0), (2, 0), (3, 1)]
    assert urls.evaluate(caps.limit(0), entries).count() == 0
    assert {r.blocked for r in urls.evaluate(caps, entries.limit(0)).collect()} == {False}
