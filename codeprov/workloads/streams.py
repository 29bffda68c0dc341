"""Streaming workloads: each runs over all of ``events`` and must equal the batch answer."""

from __future__ import annotations

from pyspark.sql import functions as F

from codeprov.clone import match
from codeprov.session import table
from codeprov.streaming import replay, state, watch, windows
from codeprov.workloads import clones


def _micros(df, column):
    return df.withColumn(column, F.unix_micros(column))


def w33(spark, sf):
    found = match.find_clones(clones._items(spark, sf), clones._documents(spark, sf))
    where = replay.place(spark, "index")
    found.select(F.col("target_id").alias("unit_id")).distinct().write.parquet(where)
    return _micros(replay.run(watch.alerts(replay.events(spark, sf), spark.read.parquet(where)), "complete"), "window_start")


def tumbling(spark, sf):
    return _micros(replay.run(windows.tumbling(replay.events(spark, sf)), "complete"), "window_start")


def sliding(spark, sf):
    return _micros(replay.run(windows.tumbling(replay.events(spark, sf), "6 hours", "1 hour"), "complete"), "window_start")


def session(spark, sf):
    return _micros(replay.run(windows.sessions(replay.events(spark, sf)), "complete"), "session_start")


def dedup(spark, sf):
    return replay.run(windows.first_seen(replay.events(spark, sf), ["user_id", "event_type"]), "append")


def followed(spark, sf):
    return replay.run(windows.followed(replay.events(spark, sf), "signup", "purchase", "1 DAY"), "append")


def chain(spark, sf):
    return replay.run(state.chains(replay.events(spark, sf)), "update")


#: Days after the first event at which a further part of the events has arrived.
ARRIVALS = (10, 20)


def _arrivals(spark, sf):
    """Events in order of time in three parts; every fiftieth comes last, after all others."""
    e = table(spark, sf, "events")
    since = F.datediff("ts", F.lit(e.agg(F.min("ts")).first()[0]))
    part = F.when(F.col("event_id") % 50 == 0, len(ARRIVALS) + 1).otherwise(sum((F.when(since >= d, 1).otherwise(0) for d in ARRIVALS), F.lit(0)))
    return [e.where(F.coalesce(part, F.lit(0)) == k) for k in range(len(ARRIVALS) + 2)]


def late(spark, sf):
    """Hours as the stream counted them (the newest count of each), as a batch counts them, and rows that came too late."""
    log = replay.arrive(_arrivals(spark, sf), windows.tumbling, "update")
    stream = replay.newest(log, ["window_start", "event_type"])
    batch = windows.tumbling(table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))).withColumnRenamed("n", "n_all")
    both = batch.join(stream, ["window_start", "event_type"], "left").na.fill(0, ["n"])
    return _micros(both.select("window_start", "event_type", "n_all", F.col("n").alias("n_stream"), (F.col("n_all") - F.col("n")).alias("n_late")), "window_start")


def similar(spark, sf):
    """Alerts of documents that arrive in three parts, by their text against the items."""
    d = table(spark, sf, "documents").select("doc_id", "text")
    parts = [d.where(F.coalesce(F.pmod("doc_id", F.lit(3)), F.lit(0)) == k) for k in range(3)]
    log = replay.arrive(parts, lambda s: s, "append", watch.similar(clones._items(spark, sf), "doc_id"), watermark=None)
    return log.select(F.col("query_id").alias("item_id"), F.col("target_id").alias("doc_id"), F.round("score", 6).alias("score"))


QUERIES = {
    "W33_stream_watch": w33,
    "ST3_tumbling": tumbling,
    "ST3_sliding": sliding,
    "ST4_session": session,
    "ST5_dedup": dedup,
    "ST7_stream_join": followed,
    "ST8_state": chain,
    "ST9_late_rows": late,
    "ST6_similar_on_arrival": similar,
}
SQL = {
    "ST9_late_rows": "WITH w AS (SELECT max(ts) - INTERVAL 1 HOUR AS mark FROM events WHERE event_id % 50 <> 0), c AS (SELECT date_trunc('hour', ts) AS h, event_type, count(*) AS n_all, count(*) FILTER (event_id % 50 = 0 AND date_trunc('hour', ts) + INTERVAL 1 HOUR <= mark) AS n_late FROM events, w WHERE ts IS NOT NULL GROUP BY ALL) SELECT epoch_us(h)::BIGINT AS window_start, event_type, n_all, n_all - n_late AS n_stream, n_late FROM c",
    "ST6_similar_on_arrival": f"WITH {clones.prints('q', 'benchmark', 'item_id')}, {clones.prints('t', 'documents', 'doc_id')}, {clones.grams('qg', 'q', 3)}, {clones.grams('tg', 't', 3)}, {clones.shared('c', 'qg', 'tg', 0.5)}, {clones.scores('s', 'c', 'q', 't')} SELECT query_id AS item_id, target_id AS doc_id, round(score, 6) AS score FROM s WHERE score >= 70",
    "W33_stream_watch": f"WITH {clones.prints('q', 'benchmark', 'item_id')}, {clones.prints('t', 'documents', 'doc_id')}, {clones.grams('qg', 'q', 3)}, {clones.grams('tg', 't', 3)}, {clones.shared('c', 'qg', 'tg', 0.5)}, {clones.scores('s', 'c', 'q', 't')} SELECT epoch_us(date_trunc('day', ts))::BIGINT AS window_start, count(*) AS alerts FROM events WHERE event_id IN (SELECT target_id FROM s WHERE score >= 70) GROUP BY ALL",
    "ST3_tumbling": "SELECT epoch_us(date_trunc('hour', ts))::BIGINT AS window_start, event_type, count(*) AS n FROM events GROUP BY ALL",
    "ST3_sliding": "SELECT epoch_us(date_trunc('hour', ts) - INTERVAL 1 HOUR * k)::BIGINT AS window_start, event_type, count(*) AS n FROM events, (SELECT unnest(range(6)) AS k) GROUP BY ALL",
    "ST4_session": "WITH g AS (SELECT *, coalesce(ts >= lag(ts) OVER w + INTERVAL 30 MINUTE, true) AS opens FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(opens::INT) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM g) SELECT user_id, epoch_us(min(ts))::BIGINT AS session_start, count(*) AS n FROM s GROUP BY user_id, k",
    "ST5_dedup": "SELECT DISTINCT user_id, event_type FROM events",
    "ST7_stream_join": "SELECT a.event_id AS first, b.event_id AS then FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'signup' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 DAY",
    "ST8_state": "WITH r AS (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id DESC) AS k FROM events), t AS (SELECT user_id, arg_max(event_type, (ts, event_id)) FILTER (event_type IN ('signup', 'purchase', 'error')) AS d FROM events GROUP BY user_id) SELECT r.user_id, (SELECT count(*) FROM events e WHERE e.user_id = r.user_id) AS events, event_type AS last_type, coalesce(d = 'signup', false) AS open_signup FROM r JOIN t USING (user_id) WHERE k = 1",
}
